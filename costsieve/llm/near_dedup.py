"""Near-duplicate documents: MinHash signatures, banding, verification on full shingle sets, and connected components.

Words are runs of non-space bytes with A-Z lower-cased; a document is the set of its distinct runs of five words, or of its one shorter run. Documents with
equal sets collapse first. The sets left get many universal hash minima; equal bands of them make candidates, a byte of each minimum screens them, and only
pairs whose full sets reach the threshold become links.

No group is ever expanded into all its pairs. First every member of a band's bucket is paired with the bucket's smallest member, and the links that hold give
components. What is left to compare are members of one bucket that are still in different components: those are put into cells of bounded size, by component where
one is large and by size of set, and each pair of cells that could hold a link compares the full sets of its members and returns only links that join components,
so that no link between different sets that share a band is lost however large the bucket. Skewed buckets are pre-aggregated before every exchange, and joins leave it to Spark to split them.

At the threshold itself a pair shares none of the 30 bands of 4 rows with a probability of 1e-5. The screen of signatures, used for pairs with a bucket's smallest
member, loses one pair in 1e9 there (half of 120 minima must agree, of which three quarters are expected to); pairs in larger buckets are compared again without it.

Defined results: a null, empty or blank text has no shingles and is linked with nothing; a null doc_id is linked with nothing, has no component and is kept;
rows that repeat a doc_id with the same words share their fate, and where the texts under one doc_id differ each is linked, kept or dropped for itself; an empty table gives an empty result; other columns are ignored (report) or passed through (``deduplicate``).
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import columns
from .components import components
from .memo import Memo, only
from .piece_bpe import slices
from .staging import Staging, ship


@dataclass(frozen=True)
class NearOptions:
    words: int = 5
    percent: int = 75  # links have 100 * intersection >= percent * union
    bands: int = 30
    rows: int = 4
    screen: float = 0.5  # least share of equal minima, by one byte each, of pairs that are verified
    cell: int = 256  # members of a bucket that are compared at once, with as many others
    codes: int = 1 << 20  # codes of a cell's members, unless one of them has more
    seed: int = 11


_WORDS: Memo | None = None
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _word_hashes() -> Memo:
    global _WORDS
    if _WORDS is None:
        import xxhash

        _WORDS = Memo(xxhash.xxh64_intdigest, room=200_000)
    return _WORDS


def shingles(text: str, size: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's shingles."""
    words = text.encode().lower().split()  # bytes: only A-Z is lowered, only ASCII white space splits
    if not words:
        return np.empty(0, np.uint64)
    codes = np.fromiter(map(_word_hashes().__getitem__, words), np.uint64, len(words))
    span = min(size, len(codes))
    total = np.full(len(codes) - span + 1, span, np.uint64)
    for j in range(span):
        total = (total ^ (total >> np.uint64(29))) * _MIX + codes[j : len(codes) - span + 1 + j]
    total = (total ^ (total >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return np.unique(total ^ (total >> np.uint64(32)))


class Signer:
    """Minima of ``bands * rows`` universal hash functions over 32 mixed bits of each shingle."""

    def __init__(self, options: NearOptions):
        rng = np.random.default_rng(options.seed)
        n = options.bands * options.rows
        self.factor = (rng.integers(0, 1 << 31, n, dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
        self.shift = rng.integers(0, 1 << 32, n, dtype=np.uint32)
        self.options = options
        self.weights = rng.integers(0, 1 << 63, (options.bands, options.rows), dtype=np.uint64) | np.uint64(1)
        self.salt = rng.integers(0, 1 << 63, options.bands, dtype=np.uint64)

    def minima(self, codes: np.ndarray) -> np.ndarray:
        low = (codes >> np.uint64(16)).astype(np.uint32)
        best = np.full(len(self.factor), 0xFFFFFFFF, np.uint32)
        for at in range(0, len(low), 512):
            block = low[at : at + 512, None] * self.factor
            block += self.shift
            np.minimum(best, block.min(axis=0), out=best)
        return best

    def bands(self, minima: np.ndarray) -> np.ndarray:
        """One 64-bit key per band; keys of different bands differ by a salt."""
        parts = minima.reshape(self.options.bands, self.options.rows).astype(np.uint64)
        total = self.salt.copy()
        for j in range(self.options.rows):
            total = (total ^ (total >> np.uint64(31))) * _MIX + parts[:, j] * self.weights[:, j]
        return (total ^ (total >> np.uint64(29))).astype(np.int64)

    @staticmethod
    def sketch(minima: np.ndarray) -> bytes:
        return ((minima * np.uint32(0x9E3779B1)) >> np.uint32(24)).astype(np.uint8).tobytes()


def sign(docs: DataFrame, options: NearOptions) -> DataFrame:
    """(doc_id, row, n_shingles, set_hash, bands, sketch); the last three are null without shingles. ``row`` names the text."""
    ship(docs.sparkSession)

    def run(batches):
        import xxhash

        signer = Signer(options)
        only(_word_hashes())
        for batch in slices(batches, "text"):
            rows = []
            for text in batch.column("text").to_pylist():
                codes = shingles(text, options.words)
                if len(codes):
                    minima = signer.minima(codes)
                    rows.append((len(codes), xxhash.xxh128_digest(codes.tobytes()), signer.bands(minima), signer.sketch(minima)))
                else:
                    rows.append((0, None, None, None))
            kinds = (pa.int64(), pa.binary(), pa.list_(pa.int64()), pa.binary())
            made = [pa.array(list(c), k) for c, k in zip(zip(*rows), kinds)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("row"), *made], ["doc_id", "row", "n_shingles", "set_hash", "bands", "sketch"])

    named = columns.documents(docs).withColumn("row", columns.row_name(F.col("text")))
    return named.mapInArrow(run, "doc_id bigint, row bigint, n_shingles bigint, set_hash binary, bands array<bigint>, sketch binary")


def shingle_sets(docs: DataFrame, options: NearOptions) -> DataFrame:
    """(doc_id, codes array<bigint>): the full sets."""
    ship(docs.sparkSession)

    def run(batches):
        only(_word_hashes())
        for batch in slices(batches, "text", 1 << 20):
            sets = [shingles(text, options.words).view(np.int64) for text in batch.column("text").to_pylist()]
            offsets = np.zeros(len(sets) + 1, np.int32)
            np.cumsum([len(s) for s in sets], out=offsets[1:])
            values = pa.array(np.concatenate(sets) if sets else np.empty(0, np.int64))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.ListArray.from_arrays(pa.array(offsets), values)], ["doc_id", "codes"])

    return columns.documents(docs).mapInArrow(run, "doc_id bigint, codes array<bigint>")


def screened(edges: DataFrame, sketches: DataFrame, options: NearOptions) -> DataFrame:
    """Edges (u, v) whose sketches agree often enough."""
    ship(edges.sparkSession)
    left = sketches.select(F.col("node").alias("u"), F.col("sketch").alias("su"))
    right = sketches.select(F.col("node").alias("v"), F.col("sketch").alias("sv"))
    least = options.screen * options.bands * options.rows

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for c in ("su", "sv"))
            keep = pa.array((a == b).sum(axis=1) >= least)
            yield pa.RecordBatch.from_arrays([batch.column("u"), batch.column("v")], ["u", "v"]).filter(keep)

    return edges.join(left, "u").join(right, "v").select("u", "v", "su", "sv").mapInArrow(run, "u bigint, v bigint")


def sets_of(docs: DataFrame, places: DataFrame, wanted: DataFrame, options: NearOptions) -> DataFrame:
    """(node, codes): the full sets of the ``wanted`` nodes, read again from the rows that ``places`` (node, doc_id, row) names."""
    own = places.join(wanted, "node", "left_semi").select("node", "rows", F.col("doc_id").alias("__doc"), F.col("row").alias("__row"))
    found = columns.documents(docs).join(own, (F.col("doc_id") == F.col("__doc")) & (columns.row_name(F.col("text")) == F.col("__row"))).select(F.col("node").alias("doc_id"), "text", "rows")
    # only rows that repeat both doc_id and text are there more than once
    texts = found.where("rows = 1").drop("rows").unionByName(found.where("rows > 1").drop("rows").dropDuplicates(["doc_id"]))
    return shingle_sets(texts, options).withColumnRenamed("doc_id", "node")


def verified(docs: DataFrame, places: DataFrame, edges: DataFrame, stage: Staging, options: NearOptions) -> DataFrame:
    """Edges (u, v) whose full sets reach the threshold. ``edges`` must be a written table."""
    nodes = edges.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    sets = stage.table(sets_of(docs, places, nodes, options), "sets")
    left = sets.select(F.col("node").alias("u"), F.col("codes").alias("cu"))
    right = sets.select(F.col("node").alias("v"), F.col("codes").alias("cv"))
    joined = edges.join(left, "u").join(right, "v")
    common = F.size(F.array_intersect("cu", "cv")).cast("bigint")
    both = joined.select("u", "v", common.alias("i"), (F.size("cu") + F.size("cv")).cast("bigint").alias("n"))
    return both.where(100 * F.col("i") >= options.percent * (F.col("n") - F.col("i"))).select("u", "v")


def bucket_members(nodes: DataFrame) -> DataFrame:
    """(key, node) of all buckets with two members or more."""
    rows = nodes.select("node", F.explode("bands").alias("key"))
    shared = rows.groupBy("key").agg(F.min("node").alias("a"), F.max("node").alias("b")).where("a < b").select("key")
    return rows.join(shared, "key").select("key", "node")


def star_edges(members: DataFrame) -> DataFrame:
    """(u, v): each member of a bucket with the bucket's smallest member."""
    pivots = members.groupBy("key").agg(F.min("node").alias("pivot"))
    return members.join(pivots, "key").where("node > pivot").select(F.col("node").alias("u"), F.col("pivot").alias("v")).distinct()


def cells_of(rows: DataFrame, stage: Staging, options: NearOptions) -> tuple[DataFrame, DataFrame]:
    """(key, node, label, cell) of mixed buckets' members, and (key, i, j) of the cells that could hold a link between different labels.

    ``rows`` are (key, n, node, label, size). A bucket of no more than a cell's members is one cell. In others, a label with enough members gets cells of its own and
    the rest share cells by size of set, so that pairs of cells with one label, or with sizes too far apart for a link, need not be compared. Cells are bounded by
    members and by codes; two that chance gives one name are compared together, which loses nothing.
    """
    wide = F.col("n") > options.cell
    large = rows.where(wide).groupBy("key", "label").agg(F.count(F.lit(1)).alias("own")).where(F.col("own") >= options.cell)
    kind = F.floor(F.log(F.col("size")) / (2 * math.log(max(100 / options.percent, 1.01))))
    homes = rows.join(large, ["key", "label"], "left").withColumn("home", F.when(F.col("own").isNotNull(), F.col("label")).otherwise(-1))
    homes = homes.withColumn("kind", F.when(wide, kind).otherwise(0))
    need = F.greatest(F.count(F.lit(1)) / options.cell, F.sum("size") / options.codes)
    groups = homes.groupBy("key", "home", "kind").agg(F.ceil(need).alias("cells"))
    name = F.xxhash64("key", "home", "kind", F.pmod(F.xxhash64("node"), F.col("cells")))
    placed = stage.table(homes.join(groups, ["key", "home", "kind"]).select("key", "node", "label", "size", name.alias("cell")), "cells")
    cells = placed.groupBy("key", "cell").agg(F.min("size").alias("low"), F.max("size").alias("high"), F.min("label").alias("a"), F.max("label").alias("b"))
    cells = stage.table(cells, "cell-bounds")
    x, y = cells.alias("x"), cells.alias("y")
    near = (100 * F.col("x.high") >= options.percent * F.col("y.low")) & (100 * F.col("y.high") >= options.percent * F.col("x.low"))
    differ = F.least("x.a", "y.a") < F.greatest("x.b", "y.b")
    pairs = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.cell") <= F.col("y.cell")) & near & differ)
    return placed.drop("size"), pairs.select("x.key", F.col("x.cell").alias("i"), F.col("y.cell").alias("j"))


def cross_links(docs: DataFrame, places: DataFrame, nodes: DataFrame, members: DataFrame, labels: DataFrame, stage: Staging, options: NearOptions) -> DataFrame:
    """(u, v): links between members of one bucket that are not in one component yet, enough of them to join what is linked.

    Buckets fall into cells of bounded size, and each pair of cells that could hold such a link is one group with the full sets of its members. A group counts
    the codes that its members share, all pairs at once, and returns a forest over components, so that nothing per pair leaves it.
    """
    ship(docs.sparkSession)
    rows = members.join(labels.withColumnRenamed("component", "label"), "node", "left").withColumn("label", F.coalesce("label", "node"))
    code = F.xxhash64("node")
    mixed = rows.groupBy("key").agg(
        F.min("label").alias("a"), F.max("label").alias("b"), F.count(F.lit(1)).alias("n"), F.bit_xor(code).alias("x"), F.sum(code.cast("decimal(38,0)")).alias("y")
    )
    # buckets with the same members are looked at once
    mixed = mixed.where("a < b AND n > 2").groupBy("n", "x", "y").agg(F.min("key").alias("key"))
    found = stage.table(rows.join(mixed.select("key", "n"), "key").join(nodes.select("node", "size"), "node"), "mixed")
    placed, pairs = cells_of(found, stage, options)
    sets = sets_of(docs, places, found.select("node").distinct(), options)
    ends = pairs.withColumn("cell", F.explode(F.array_distinct(F.array("i", "j"))))
    dealt = placed.join(ends, ["key", "cell"]).select("key", "i", "j", "node", "label")
    percent = options.percent

    def run(table: pa.Table) -> pa.Table:
        node, label = (table.column(c).to_numpy() for c in ("node", "label"))
        codes = table.column("codes").combine_chunks()
        sizes = np.asarray(codes.value_lengths()).astype(np.int64)
        return pa.table(dict(zip("uv", _forest(node, label, np.asarray(codes.flatten()), sizes, percent))), schema=pa.schema([("u", pa.int64()), ("v", pa.int64())]))

    return dealt.join(sets, "node").groupBy("key", "i", "j").applyInArrow(run, "u bigint, v bigint").distinct()


def _forest(node: np.ndarray, label: np.ndarray, codes: np.ndarray, sizes: np.ndarray, percent: int, width: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """Links between members of different labels, none between labels that earlier ones have joined."""
    names, counts = np.unique(label, return_counts=True)
    rest = np.flatnonzero(label != names[counts.argmax()])
    if not len(rest):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    owner = np.repeat(np.arange(len(node)), sizes)
    order = np.argsort(codes, kind="stable")
    codes, owner = codes[order], owner[order]
    fresh = np.r_[True, codes[1:] != codes[:-1]]
    place = np.cumsum(fresh) - 1
    shared = np.bincount(place)[place] > 1  # codes of one member are shared with none
    owner, place = owner[shared], place[shared]
    place = np.cumsum(np.r_[True, place[1:] != place[:-1]]) - 1 if len(place) else place
    common = np.zeros((len(rest), len(node)), np.float32)
    for begin in range(0, int(place[-1]) + 1 if len(place) else 0, width):
        low, high = np.searchsorted(place, (begin, begin + width))
        block = np.zeros((len(node), width), np.float32)
        block[owner[low:high], place[low:high] - begin] = 1
        common += block[rest] @ block.T
    common = np.rint(common).astype(np.int64)
    linked = 100 * common >= percent * (sizes[rest][:, None] + sizes[None, :] - common)
    linked &= label[rest][:, None] != label[None, :]
    root = {int(x): int(x) for x in names}

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    us, vs = [], []
    for r, c in zip(*np.nonzero(linked)):
        a, b = find(int(label[rest[r]])), find(int(label[c]))
        if a != b:
            root[max(a, b)] = min(a, b)
            us.append(max(node[rest[r]], node[c]))
            vs.append(min(node[rest[r]], node[c]))
    return np.array(us, np.int64), np.array(vs, np.int64)


def near_report(docs: DataFrame, options: NearOptions = NearOptions()) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept): one row per document."""
    return _decided(docs, options).drop("row")


def _decided(docs: DataFrame, options: NearOptions) -> DataFrame:
    """The report with the name of each row's text."""
    stage = Staging(docs.sparkSession, "near-dedup")
    signed = stage.table(sign(docs, options), "signed")
    named = signed.where(F.col("set_hash").isNotNull() & F.col("doc_id").isNotNull())
    rows = named.groupBy("set_hash", "doc_id", "row").agg(F.count(F.lit(1)).alias("rows"))
    sets = rows.groupBy("set_hash").agg(F.min(F.struct("doc_id", "row", "rows")).alias("first")).select("set_hash", "first.*")
    places = stage.table(sets.withColumn("node", F.monotonically_increasing_id()), "distinct-sets")  # sets are numbered, as doc_ids need not be their own
    nodes = named.join(places, ["set_hash", "doc_id", "row"]).select("node", "rows", "bands", "sketch", F.col("n_shingles").alias("size"))
    nodes = stage.table(nodes.where("rows = 1").unionByName(nodes.where("rows > 1").dropDuplicates(["node"])).drop("rows"), "nodes")

    members = stage.table(bucket_members(nodes), "members")

    stars = stage.table(screened(star_edges(members), nodes, options), "edges")
    first = components(stage.table(verified(docs, places, stars, stage, options), "links"), stage)
    first = stage.table(first, "components")
    more = cross_links(docs, places, nodes, members, first, stage, options)
    known = first.select(F.col("node").alias("u"), F.col("component").alias("v")).where("u <> v")
    final = components(known.unionByName(more), stage)

    joined = stage.table(places.join(final, "node", "left").select("set_hash", "doc_id", F.coalesce("component", "node").alias("component")), "joined")
    least = joined.groupBy("component").agg(F.min("doc_id").alias("least"))
    of_set = stage.table(joined.join(least, "component").select("set_hash", F.col("least").alias("component")), "of-set")  # plain sides can be split where copies are many
    found = signed.drop("bands", "sketch").join(of_set, "set_hash", "left")
    linked = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return found.select("doc_id", "row", "n_shingles", linked.alias("component_id"), linked.eqNullSafe(F.col("doc_id")).alias("kept"))


def deduplicate(docs: DataFrame, options: NearOptions = NearOptions()) -> DataFrame:
    """The rows of each component's smallest doc_id, and all that are linked with nothing, with all their columns."""
    return columns.without(docs, _decided(docs, options).where(~F.col("kept")).select("doc_id", "row").distinct())


#: Brute force: all pairs that share a shingle, and the closure of their links.
ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
       '[\x20\x09-\x0D]+'), lambda x: x <> '') AS t FROM documents),
     sh AS (SELECT DISTINCT doc_id, array_to_string(list_slice(t, i, i + 4), ' ') AS s FROM (SELECT doc_id, t, unnest(range(1, greatest(len(t) - 3, 2))) AS i FROM w WHERE len(t) > 0)),
     n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
     pairs AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY ALL),
     links AS (SELECT x, y FROM pairs JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * c >= 75 * (nx.n + ny.n - c)),
     sides AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
     reach(doc_id, root) AS (SELECT doc_id, doc_id FROM w UNION SELECT b.y, r.root FROM reach r JOIN sides b ON b.x = r.doc_id)
SELECT r.doc_id, coalesce(any_value(n.n), 0) AS n_shingles, min(r.root) AS component_id, r.doc_id = min(r.root) AS kept
FROM reach r LEFT JOIN n ON n.doc_id = r.doc_id GROUP BY r.doc_id
"""
