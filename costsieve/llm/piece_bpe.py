"""Exact merge-type encoding with a SentencePiece BPE vocabulary, by backtracking instead of merging.

An Aho-Corasick automaton finds the longest vocabulary piece at a position, a table the next shorter ones. The encoder tries them from the longest down and
keeps a piece only if it is compatible with the piece before it: merging the two pieces' characters again must give back exactly these two.
A position from which no piece works is marked in a bitfield and the last piece is taken back. Since a sequence whose neighbours are all compatible
is the one that merging makes, a marked position can never be right, so each position fails at most once.

Defined results: a null or empty text has no pieces before the end id; characters outside the vocabulary become their UTF-8 bytes'
pieces; a null ids array decodes to the empty text; a null doc_id and repeated rows are carried through; other columns are ignored.
"""

from __future__ import annotations

import re
import sys
from array import array
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from . import columns
from .memo import Memo, only
from .staging import ship

MARK = "\u2581"  # stands for a space in the vocabulary
LATIN = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u024f"  # letters, and letters still when lower-cased
LITTLE = sys.byteorder == "little"
_ENCODERS: dict[str, "PieceEncoder"] = {}


class PieceEncoder:
    def __init__(self, model_path: str):
        import ahocorasick
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_path)
        self.end_id, self.unknown_id = model.eos_id(), model.unk_id()
        self.ids: dict[str, int] = {}
        self.scores: dict[str, float] = {}
        self.bytes_to_id: dict[int, int] = {}
        self.surface: list[bytes] = []
        for i in range(model.vocab_size()):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                value = int(piece[3:5], 16)
                self.bytes_to_id[value] = i
                self.surface.append(bytes([value]))
            elif model.is_unknown(i):
                self.surface.append(" ⁇ ".encode())
            elif model.is_control(i):
                self.surface.append(b"")
            else:
                self.ids[piece], self.scores[piece] = i, model.get_score(i)
                self.surface.append(piece.replace(MARK, " ").encode())
        if any(MARK in piece.lstrip(MARK) for piece in self.ids):
            raise ValueError("pieces that hold a space after other characters are not supported")
        self.code = {i: piece for piece, i in self.ids.items()}
        own = {piece for piece in self.ids if len(piece) == 1 or self.merge(piece) == [piece]}
        self.machine = ahocorasick.Automaton()
        for piece in own:
            self.machine.add_word(piece, (len(piece), self.ids[piece]))
        self.machine.make_automaton()
        self.shorter: dict[int, int] = {}  # the longest piece that a piece begins with, itself aside
        for piece in own:
            shorter = next((self.ids[piece[:n]] for n in range(len(piece) - 1, 0, -1) if piece[:n] in own), None)
            if shorter is not None:
                self.shorter[self.ids[piece]] = shorter
        self.size = {self.ids[piece]: len(piece) for piece in own}
        self.fits: dict[int, bool] = {}
        self.parts = Memo(self._part, room=400_000)
        self.cut = self._cutter().findall

    def merge(self, text: str) -> list[str]:
        """The definition: join the neighbours whose union scores best, the leftmost of equals, until none is a piece."""
        parts, scores = list(text), self.scores
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                score = scores.get(parts[i] + parts[i + 1])
                if score is not None and (best is None or score > best):
                    best, at = score, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _piece(self, i: int) -> str:
        return self.code[i] if i in self.code else chr(i - len(self.surface))

    def _fit(self, left: int, right: int) -> bool:
        """Whether merging the characters of two neighbours again gives back the two."""
        key = left << 32 | right
        found = self.fits.get(key)
        if found is None:
            a, b = self._piece(left), self._piece(right)
            if len(self.fits) >= 500_000:
                self.fits.clear()
            found = self.fits[key] = self.merge(a + b) == [a, b]
        return found

    def longest(self, text: str, at: int) -> int:
        """The longest piece that starts at ``at``; a character outside the vocabulary counts as vocabulary size plus code point."""
        for end, (length, piece) in self.machine.iter_long(text, at):
            if end - length + 1 == at:
                return piece
            break
        return len(self.surface) + ord(text[at])

    def _next(self, text: str, at: int, piece: int) -> int | None:
        """The next candidate at ``at`` after ``piece``."""
        found = self.shorter.get(piece)
        if found is None and self.size.get(piece, 1) > 1:
            return len(self.surface) + ord(text[at])
        return found

    def pieces(self, text: str) -> list[int]:
        greedy = [match for _, match in self.machine.iter_long(text)]
        out = [piece for _, piece in greedy]
        fits = self.fits
        if sum([length for length, _ in greedy]) == len(text):
            for left, right in zip(out, out[1:]):
                fit = fits.get(left << 32 | right)
                if not fit and (fit is not None or not self._fit(left, right)):
                    break
            else:
                return out
        return self._backtrack(text)

    def _backtrack(self, text: str) -> list[int]:
        size, length = len(text), self.size
        failed = bytearray(size // 8 + 1)
        out: list[int] = []
        at, piece, fits = 0, self.longest(text, 0), self.fits
        while at < size:
            while piece is not None:
                end = at + length.get(piece, 1)
                if not failed[end >> 3] >> (end & 7) & 1:
                    if not out:
                        break
                    fit = fits.get(out[-1] << 32 | piece)
                    if fit or fit is None and self._fit(out[-1], piece):
                        break
                piece = self._next(text, at, piece)
            if piece is None:
                failed[at >> 3] |= 1 << (at & 7)
                piece = out.pop()
                at -= length.get(piece, 1)
                piece = self._next(text, at, piece)
            else:
                out.append(piece)
                at = end
                if at < size:
                    piece = self.longest(text, at)
        return out

    def _part(self, text: str) -> bytes:
        outside = len(self.surface)
        found: list[int] = []
        for i in self.pieces(text):
            if i < outside:
                found.append(i)
            else:
                found += [self.bytes_to_id.get(b, self.unknown_id) for b in chr(i - outside).encode()]
        return array("I", found).tobytes() if LITTLE else b"".join(i.to_bytes(4, "little") for i in found)

    def _cutter(self) -> re.Pattern:
        """Cuts a text only between neighbours that no piece holds side by side, so that no merge crosses a cut.

        Spaces never follow other characters inside a piece; of the usual marks those are used that no piece holds after a Latin letter.
        """
        pairs = {piece[i : i + 2] for piece in self.ids for i in range(len(piece) - 1)}
        after = {pair[1] for pair in pairs if re.match(f"[{LATIN}]", pair[0])}
        marks = "".join(re.escape(c) for c in ".,;:!?|)" if c not in after)
        alone = "" if any("\n" in pair for pair in pairs) else "\n"
        line = f"|{alone}" if alone else ""
        return re.compile(f"{MARK}*[{LATIN}]++(?=[{MARK}{marks}{alone}]|\\Z){line}|{MARK}*[^{MARK}{alone}]+|{MARK}+")

    def encode(self, text: str) -> bytes:
        """Little-endian 32-bit ids of a whole text with the end id."""
        found = list(map(self.parts.__getitem__, self.cut(MARK + text.replace(" ", MARK)))) if text else []
        found.append(self.end_id.to_bytes(4, "little"))
        return b"".join(found)

    def decode(self, ids: list[int]) -> str:
        """The text of ids: the space put before the first piece goes, control pieces are silent."""
        surface = self.surface
        text = b"".join([surface[i] for i in ids]).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


def encoder(model_path: str) -> PieceEncoder:
    if model_path not in _ENCODERS:
        _ENCODERS[model_path] = PieceEncoder(model_path)
    return _ENCODERS[model_path]


def slices(batches: Iterator[pa.RecordBatch], by: str, size: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that the values of one column stay near ``size`` bytes."""
    for batch in batches:
        begin, held = 0, 0
        sizes = [0 if v is None else v for v in _lengths(batch.column(by))]
        for i, n in enumerate(sizes):
            if held and held + n > size:
                yield batch.slice(begin, i - begin)
                begin, held = i, 0
            held += n
        if begin < batch.num_rows:
            yield batch.slice(begin)


def _lengths(column: pa.Array) -> list[int]:
    import pyarrow.compute as pc

    kind = column.type
    return (pc.list_value_length(column) if pa.types.is_list(kind) or pa.types.is_large_list(kind) else pc.binary_length(column)).to_pylist()


def _encoding(model_path: str):
    def run(batches):
        import numpy as np

        own = encoder(model_path)
        only(own.parts)
        for batch in slices(batches, "text"):
            coded = [own.encode(text) for text in batch.column("text").to_pylist()]
            offsets = np.zeros(len(coded) + 1, np.int32)
            np.cumsum([len(c) // 4 for c in coded], out=offsets[1:])
            values = pa.Array.from_buffers(pa.int32(), int(offsets[-1]), [None, pa.py_buffer(b"".join(coded))])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.ListArray.from_arrays(pa.array(offsets), values)], ["doc_id", "ids"])

    return run


def _decoding(model_path: str):
    def run(batches):
        import numpy as np

        own = encoder(model_path)
        for batch in slices(batches, "ids", 1 << 20):
            ids = batch.column("ids")
            values, ends = ids.flatten().to_numpy(zero_copy_only=False), np.cumsum([0 if n is None else n for n in _lengths(ids)])
            texts = [own.decode(values[a:b].tolist()) for a, b in zip([0, *ends[:-1].tolist()], ends.tolist())]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), ids, pa.array(texts, pa.string())], ["doc_id", "ids", "text"])

    return run


def encode(docs: DataFrame, model_path: str) -> DataFrame:
    """(doc_id bigint, ids array<int>) of every document, the end id included."""
    ship(docs.sparkSession)
    return columns.documents(docs).mapInArrow(_encoding(model_path), "doc_id bigint, ids array<int>")


def decode(coded: DataFrame, model_path: str) -> DataFrame:
    """(doc_id bigint, ids array<int>, text string) of encoded documents."""
    ship(coded.sparkSession)
    return columns.pick(coded, doc_id="doc_id", ids="ids").mapInArrow(_decoding(model_path), "doc_id bigint, ids array<int>, text string")


def round_trip(docs: DataFrame, model_path: str) -> DataFrame:
    """(doc_id, ids, text): encoded, and decoded from the ids again by the same worker."""
    ship(docs.sparkSession)
    code, text = _encoding(model_path), _decoding(model_path)
    return columns.documents(docs).mapInArrow(lambda batches: text(code(batches)), "doc_id bigint, ids array<int>, text string")
