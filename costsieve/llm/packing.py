"""Best-fit packing of token sequences, in bulk-synchronous sweeps over range-sorted pieces and gaps.

Pieces are taken in bands of length, the longest first: band b holds lengths from capacity / 2**b down to, but without, half of that. A superstep of a band
sorts its pieces and the gaps that could hold one, together, into ranges of size over all tasks. Each task sweeps its range from the largest size down with a stack: a gap goes onto it, a piece takes the topmost,
which is its successor, the smallest free gap that holds it; pieces that want the same gap get it, and the next larger ones, in rank order. What a range cannot match inside is resolved between ranges: every task tells how many
pieces and gaps it has left, these counts, two a task, are swept in the same way, and the leftovers meet by their match numbers in a join. So a superstep gives exactly the pairs that one sweep over all rows would.
Then the gaps shrink, and the superstep repeats with the pieces left until no gap holds any of them; those open new sequences, 2**b ranks in a row to each, whose gaps join the others. A gap with room for several pieces of a band enters as several slots, and of the wide gaps only the
smallest enter, as many as the pieces can ask for.

Nothing is gathered on the driver but counts per task, per band and per size of gap. Range keys end in a row's number, so lengths that a third of all pieces have are split like any other.

Defined results: a null or empty text is the end id alone; a document longer than ``capacity`` becomes pieces of ``capacity`` ids whose first may be
shorter; rows that repeat a doc_id are documents of their own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import columns
from .staging import Staging, ship

PIECE = "doc_id bigint, piece int, start bigint, length bigint, ids binary, pid bigint"
SWEPT = "kind int, size int, pid bigint, sid bigint, slot int, part int, rank bigint"
PLACED, PIECE_LEFT, SLOT_LEFT = 0, 1, 2
RANGE_ROWS = 1 << 20  # pieces and gaps that one task sweeps


def cut(coded: DataFrame, capacity: int = 2048, encoding=None) -> DataFrame:
    """Pieces of (doc_id, ids), each with a number of its own.

    With ``encoding``, work on batches as ``byte_tokens.encoding`` gives it, the rows are documents, and encoding and cutting share a worker.
    """
    ship(coded.sparkSession)

    def run(batches):
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 40
        for batch in encoding(batches) if encoding else batches:
            rows: list[tuple] = []
            for doc, ids in zip(batch.column("doc_id").to_pylist(), batch.column("ids").to_pylist()):
                total = len(ids) // 4
                begin, piece = 0, 0
                end = total % capacity or min(total, capacity)
                while begin < total:
                    rows.append((doc, piece, begin, end - begin, ids[4 * begin : 4 * end], number))
                    begin, end, piece, number = end, end + capacity, piece + 1, number + 1
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.int64())
            names = ["doc_id", "piece", "start", "length", "ids", "pid"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [()] * 6, kinds)], names)

    source = columns.documents(coded) if encoding else columns.pick(coded, doc_id="doc_id", ids="ids")
    return source.mapInArrow(run, PIECE)


def matched(is_gap: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(pieces, their gaps, pieces left, gaps left) as places in a list sorted from the largest size down, gaps before pieces of their size.

    Every piece takes the nearest gap before it that no piece between them has taken.
    """
    depth = np.cumsum(np.where(is_gap, 1, -1))
    least = np.minimum.accumulate(np.minimum(depth, 0)) if len(depth) else depth
    left = ~is_gap & (least < np.r_[0, least[:-1]]) if len(depth) else np.zeros(0, bool)
    level = depth - least + ~is_gap  # a gap's level after it came, a piece's before it took one
    own = np.flatnonzero(~left)
    own = own[np.argsort(level[own], kind="stable")]
    pair = is_gap[own[:-1]] & ~is_gap[own[1:]] & (level[own[:-1]] == level[own[1:]])
    gaps, pieces = own[:-1][pair], own[1:][pair]
    free = is_gap.copy()
    free[gaps] = False
    return pieces, gaps, np.flatnonzero(left), np.flatnonzero(free)


def linked(counts: list[tuple[int, int]]) -> tuple[list[tuple[int, int, int, int, int, int]], list[int]]:
    """Matches between ranges. ``counts`` holds each range's (pieces left, gaps left), from the largest sizes down; inside a range the pieces left stand before the gaps left.

    Returns runs (range of the pieces, first rank, range of the gaps, last rank, how many, first match number): ranks of pieces count up, those of gaps down; and how many pieces each range has matched.
    """
    stack: list[list[int]] = []
    runs, done, number = [], [], 0
    for part, (pieces, gaps) in enumerate(counts):
        at = 0
        while at < pieces and stack:
            own, free = stack[-1]
            n = min(free, pieces - at)
            runs.append((part, at, own, free - 1, n, number))
            at, number = at + n, number + n
            if n == free:
                stack.pop()
            else:
                stack[-1][1] -= n
        done.append(at)
        if gaps:
            stack.append([part, gaps])
    return runs, done


def _swept(items: DataFrame, ranges: int) -> DataFrame:
    """Rows of SWEPT from (size, piece, id, slot): pairs inside ranges, and what is left with its rank in its range."""
    order = [F.desc("size"), F.asc("piece"), F.asc("id"), F.asc("slot")]

    def run(batches):
        from pyspark import TaskContext

        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows = pa.Table.from_batches(held)
        size, piece, name, slot = (rows.column(c).to_numpy() for c in ("size", "piece", "id", "slot"))
        part = TaskContext.get().partitionId()
        pieces, gaps, pieces_left, gaps_left = matched(~piece)
        blocks = ((PLACED, pieces, gaps), (PIECE_LEFT, pieces_left, None), (SLOT_LEFT, None, gaps_left))
        for kind, own, gap in blocks:
            at = own if own is not None else gap
            n = len(at)
            arrays = (
                pa.array(np.full(n, kind, np.int32)),
                pa.array(size[at].astype(np.int32)),
                pa.array(name[own]) if own is not None else pa.nulls(n, pa.int64()),
                pa.array(name[gap]) if gap is not None else pa.nulls(n, pa.int64()),
                pa.array(slot[gap].astype(np.int32)) if gap is not None else pa.nulls(n, pa.int32()),
                pa.array(np.full(n, part, np.int32)),
                pa.array(np.arange(n, dtype=np.int64)),
            )
            yield pa.RecordBatch.from_arrays(list(arrays), [c.split()[0] for c in SWEPT.split(", ")])

    return items.repartitionByRange(ranges, *order).sortWithinPartitions(*order).mapInArrow(run, SWEPT)


def _across(swept: DataFrame, runs: list[tuple]) -> DataFrame:
    """(pid, sid, slot, size): pieces and slots left that the runs, two a range at most, bring together."""
    table = np.array(runs, np.int64).reshape(-1, 6)

    def run(batches):
        by_piece = table[np.lexsort((table[:, 1], table[:, 0]))]
        by_slot = table[np.lexsort((table[:, 3], table[:, 2]))]
        for batch in batches:
            kind, part, rank = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("kind", "part", "rank"))
            number = np.full(len(kind), -1, np.int64)
            for which, own, range_at, rank_at in ((PIECE_LEFT, by_piece, 0, 1), (SLOT_LEFT, by_slot, 2, 3)):
                code = own[:, range_at] << 40 | own[:, rank_at]
                want = part << 40 | rank
                # a piece's run is the last that begins at or before it, a slot's the first that ends at or after it
                at = np.searchsorted(code, want, side="right") - 1 if which == PIECE_LEFT else np.searchsorted(code, want, side="left")
                inside = (kind == which) & (at >= 0) & (at < len(own))
                found = own[np.clip(at, 0, len(own) - 1)]
                step = rank - found[:, 1] if which == PIECE_LEFT else found[:, 3] - rank
                inside &= (found[:, range_at] == part) & (step >= 0) & (step < found[:, 4])
                number[inside] = (found[:, 5] + step)[inside]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(number)], [*batch.schema.names, "number"])

    left = swept.where(F.col("kind") != PLACED).mapInArrow(run, f"{SWEPT}, number bigint").where("number >= 0")
    pieces = left.where(F.col("kind") == PIECE_LEFT).select("number", "pid", "size")
    slots = left.where(F.col("kind") == SLOT_LEFT).select("number", "sid", "slot")
    return pieces.join(slots, "number").select("pid", "sid", "slot", "size")


def _slots(gap: Column, room: int) -> Column:
    return F.greatest(F.lit(1), F.floor(gap / room)).cast("int")


def sweep(pieces: DataFrame, gaps: DataFrame, room: int, stage: Staging, ranges: int = 1) -> tuple[DataFrame, DataFrame, int, int]:
    """One superstep over (pid, size) and (sid, gap): (placed (pid, sid, slot, size), left (pid, size, rank), pieces left, the shortest of them); the frames are written tables or plain views of them.

    ``rank`` numbers what is left from the longest down. A gap enters as slots of ``room``, the longest piece's length, the last of which holds what is over.
    """
    slots = _slots(F.col("gap"), room)
    slots = gaps.withColumn("slots", slots).withColumn("slot", F.explode(F.sequence(F.lit(0), F.col("slots") - 1)))
    size = F.when(F.col("slot") < F.col("slots") - 1, F.lit(room)).otherwise(F.col("gap") - (F.col("slots") - 1) * room)
    items = pieces.select(F.col("size").cast("int").alias("size"), F.lit(True).alias("piece"), F.col("pid").alias("id"), F.lit(0).alias("slot")).unionByName(
        slots.select(size.cast("int").alias("size"), F.lit(False).alias("piece"), F.col("sid").alias("id"), "slot")
    )
    swept = stage.table(_swept(items, ranges), "swept")
    sums = swept.where(F.col("kind") != PLACED).groupBy("part", "kind").agg(F.count(F.lit(1)).alias("n"), F.min("size").alias("least")).collect()  # two a range
    told, least = {(r["part"], r["kind"]): r["n"] for r in sums}, {r["part"]: r["least"] for r in sums if r["kind"] == PIECE_LEFT}
    parts = max((p for p, _ in told), default=-1) + 1
    runs, done = linked([(told.get((p, PIECE_LEFT), 0), told.get((p, SLOT_LEFT), 0)) for p in range(parts)])
    placed = swept.where(F.col("kind") == PLACED).select("pid", "sid", "slot", "size")
    left = swept.where(F.col("kind") == PIECE_LEFT)
    if runs:
        placed = placed.unionByName(stage.table(_across(swept, runs), "across"))
    first, base = [], 0
    for p in range(parts):
        first.append((p, done[p], base))
        base += told.get((p, PIECE_LEFT), 0) - done[p]
    if parts > 1:
        starts = pieces.sparkSession.createDataFrame(first, "__part int, __done bigint, __base bigint")
        left = left.join(F.broadcast(starts), F.col("part") == F.col("__part")).where("rank >= __done")  # one row a range
        left = left.select("pid", "size", (F.col("__base") + F.col("rank") - F.col("__done")).alias("rank"))
    # a range's last pieces, the shortest, are the ones that stay unmatched
    return placed, left.select("pid", "size", "rank"), base, min((least[p] for p in least if told[p, PIECE_LEFT] > done[p]), default=0)


def place(pieces: DataFrame, stage: Staging, capacity: int = 2048, range_rows: int = RANGE_ROWS) -> DataFrame:
    """(pid, sequence_id, offset) of (pid, length), which must be a written table."""
    spark = pieces.sparkSession
    bands = max(1, capacity.bit_length() - 4)  # the last one holds all lengths of less than 16 or so
    upper = [capacity >> b for b in range(bands)] + [0]
    number = sum(((F.col("length") <= u).cast("int") for u in upper[1:-1]), F.lit(0))
    work = pieces.select("pid", F.col("length").alias("size"), number.alias("band"))
    counts = {r["band"]: r["n"] for r in work.groupBy("band").agg(F.count(F.lit(1)).alias("n")).collect()}
    gaps = stage.table(spark.createDataFrame([], "sid bigint, gap bigint"), "gaps")
    done, made, turn = [], 0, 0
    for band in sorted(counts):
        left, n, least, room = work.where(F.col("band") == band).select("pid", "size"), counts[band], upper[band + 1] + 1, upper[band]
        while n:
            held = {r["gap"]: r["n"] for r in gaps.where(F.col("gap") >= least).groupBy("gap").agg(F.count(F.lit(1)).alias("n")).collect()} if made else {}  # ``capacity`` rows at most
            if "rank" in left.columns and not held:
                break
            fit, slots = _asked(gaps, held, least, room, n, turn)
            placed, left, n, least = sweep(left, fit, room, stage, -(-(n + slots) // range_rows))
            done.append(placed.withColumn("turn", F.lit(turn)))
            turn += 1
            if slots:
                gaps = _shrunk(gaps, placed.select("sid", (-F.col("size")).alias("d")), stage)
        if n:
            each = 1 << band
            opened = left.select("pid", (F.floor(F.col("rank") / each) + made).alias("sid"), (F.col("rank") % each).cast("int").alias("slot"), "size", F.lit(turn).alias("turn"))
            done.append(opened)
            turn += 1
            whole = F.when(F.col("slot") == 0, F.lit(capacity)).otherwise(F.lit(0))
            gaps = _shrunk(gaps, opened.select("sid", (whole - F.col("size")).alias("d")), stage)
            made += -(-n // each)
    every = reduce(DataFrame.unionByName, done) if done else spark.createDataFrame([], "pid bigint, sid bigint, slot int, size bigint, turn int")
    before = Window.partitionBy("sid").orderBy("turn", "slot").rowsBetween(Window.unboundedPreceding, -1)  # a sequence's pieces
    return every.select("pid", F.col("sid").alias("sequence_id"), F.coalesce(F.sum("size").over(before), F.lit(0)).cast("bigint").alias("offset"))


def _asked(gaps: DataFrame, held: dict[int, int], least: int, room: int, n: int, turn: int) -> tuple[DataFrame, int]:
    """The gaps that n pieces can ask for, and how many slots they make: all that are short of ``room``, then the smallest wider ones until every piece is sure of one.

    Larger gaps are nobody's successor then. Of the last size only a share by hash takes part; should it fall short, the next superstep asks for more.
    """
    slots, sure = sum(c for g, c in held.items() if g < room), 0
    for gap in sorted(g for g in held if g >= room):
        each, count = gap // room, held[gap]
        if sure + each * count >= n:
            wanted = min(count, int(1.25 * (n - sure) / each) + 16)
            some = F.pmod(F.xxhash64("sid", F.lit(turn)), F.lit(1 << 30)) < int((1 << 30) * wanted / count)
            return gaps.where((F.col("gap") >= least) & ((F.col("gap") < gap) | ((F.col("gap") == gap) & some))), slots + sure + each * wanted
        sure += each * count
    return gaps.where(F.col("gap") >= least), slots + sure


def _shrunk(gaps: DataFrame, changes: DataFrame, stage: Staging) -> DataFrame:
    """Gaps after changes (sid, d); full sequences are left out."""
    both = gaps.select("sid", F.col("gap").cast("bigint").alias("d")).unionByName(changes.select("sid", F.col("d").cast("bigint").alias("d")))
    return stage.table(both.groupBy("sid").agg(F.sum("d").alias("gap")).where("gap > 0"), "gaps")


def pack(coded: DataFrame, capacity: int = 2048, keep_ids: bool = False, encoding=None, range_rows: int = RANGE_ROWS) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset), with the pieces' ids if asked for."""
    stage = Staging(coded.sparkSession, "packing")
    pieces = cut(coded, capacity, encoding).withColumn("ids_crc32", F.crc32("ids"))
    pieces = stage.table(pieces if keep_ids else pieces.drop("ids"), "pieces")
    return pieces.join(place(pieces.select("pid", "length"), stage, capacity, range_rows), "pid").drop("pid")


def assemble(packed: DataFrame) -> DataFrame:
    """(sequence_id, ids binary): the token sequences themselves, from pieces packed with their ids."""
    parts = packed.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", F.hex("ids").alias("ids")))).alias("parts"))
    return parts.select("sequence_id", F.unhex(F.array_join(F.col("parts.ids"), "")).alias("ids"))
