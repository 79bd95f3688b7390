"""Token ids from vocabularies of the ``tokenizers`` library, one call per distinct chunk.

No pre-token of these vocabularies holds white space after another character, so a text splits before each run of white space without any change
of its ids. Chunks repeat far more often than texts; each worker remembers a bounded number of them.

Defined results: a null or empty text gives the end id only; strings of special tokens inside a text are ordinary text; a null doc_id and repeated
rows are carried through; other columns are ignored.
"""

from __future__ import annotations

import os
import re
import sys
from array import array

import pyarrow as pa
from pyspark.sql import DataFrame

from . import columns
from .memo import Memo, only
from .piece_bpe import LATIN, slices
from .staging import ship

#: The characters of Unicode's White_Space property.
WHITE = "\t\n\x0b\x0c\r \x85\xa0  -     　"
#: Marks that begin a pre-token of their own after a Latin letter (the apostrophe may not).
_END = f"(?=[{WHITE}.,;:!?|)]|\\Z)"
_WITH_LEADING = re.compile(f"[{WHITE}]*[{LATIN}]++{_END}|[{WHITE}]*[^{WHITE}]+|[{WHITE}]+")
_WORDS = re.compile(f"[{LATIN}]++{_END}|[^{WHITE}]+")
_LETTERS = re.compile(f" ?[{LATIN}]+")
#: Characters that are their own canonical form and have one lower-case letter at most.
_PLAIN = re.compile("[\\x00-\u012f\u0131-\u024f]*")
#: Byte-level vocabularies write bytes as letters: printable ones stand for themselves, the others for 256 and up, in order.
_PRINTED = [*range(33, 127), *range(161, 173), *range(174, 256)]
BYTE_LETTERS = {b: b for b in _PRINTED} | {b: 256 + i for i, b in enumerate(sorted(set(range(256)) - set(_PRINTED)))}
_CODERS: dict[tuple, "ChunkCoder"] = {}


class ChunkCoder:
    def __init__(self, path: str, keep_white: bool):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = True
        self.keep_white, self.model = keep_white, self.library.model
        self.find = (_WITH_LEADING if keep_white else _WORDS).findall
        self.chunks = Memo(self._chunk)

    def _chunk(self, chunk: str) -> bytes:
        """Latin letters are one pre-token, which goes to the library's model at once; anything else takes the library's whole way."""
        if chunk[0] == "\n" and len(chunk) > 1 and chunk[1] not in WHITE:
            return self.chunks["\n"] + self.chunks[chunk[1:]]
        if _LETTERS.fullmatch(chunk):
            text = chunk if self.keep_white else chunk.lower()
            ids = [t.id for t in self.model.tokenize(text.encode().decode("latin-1").translate(BYTE_LETTERS))]
        else:
            ids = self.library.encode(chunk, add_special_tokens=False).ids
        codes = array("I", ids)
        if sys.byteorder != "little":
            codes.byteswap()
        return codes.tobytes()

    def encode(self, text: str) -> bytes:
        """Little-endian 32-bit ids of the whole text, without an end id."""
        if not self.keep_white and _PLAIN.fullmatch(text):
            text = text.lower()  # the library would do so later; capitals would only be further chunks
        return b"".join(map(self.chunks.__getitem__, self.find(text)))


def coder(path: str, keep_white: bool) -> ChunkCoder:
    if (path, keep_white) not in _CODERS:
        _CODERS[path, keep_white] = ChunkCoder(path, keep_white)
    return _CODERS[path, keep_white]


def encoding(path: str, end_id: int, keep_white: bool):
    """The work on batches of (doc_id, text): ids of each whole text and the end id as little-endian 32-bit numbers."""
    end = end_id.to_bytes(4, "little")

    def run(batches):
        own = coder(path, keep_white)
        only(own.chunks)
        for batch in slices(batches, "text"):
            coded = [own.encode(text) + end for text in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(coded, pa.binary())], ["doc_id", "ids"])

    return run


def encode(docs: DataFrame, path: str, end_id: int, keep_white: bool) -> DataFrame:
    """(doc_id bigint, ids binary)."""
    ship(docs.sparkSession)
    return columns.documents(docs).mapInArrow(encoding(path, end_id, keep_white), "doc_id bigint, ids binary")
