"""SentencePiece encoding and decoding over a table of distinct chunks.

Where no piece of the model crosses from a letter to a white space marker (or holds a line end), a text falls
into chunks that are segmented independently.  Each task segments every distinct chunk once, keeps the ids in a
table and joins them back by position.  The condition is read from the vocabulary and probed; a model that fails
it is run on whole texts.
"""

from __future__ import annotations

import re
import struct
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_text

MARK = "▁"
#: Texts on which chunked and whole encoding must agree before chunks are used.
PROBES = ("", " ", "a", " a", "a ", "a  b\n", "\n\na\n b", "▁a ▁▁b", "\tx\t y\r\n", "ﬁ ① Å å 　x", "1234 5.6, \U0001f600\U0001f600 z")


class ChunkCodec:
    def __init__(self, path: str, cached: int = 400_000):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.ends = struct.pack("<I", self.model.bos_id()), struct.pack("<I", self.model.eos_id())
        self.chunk = re.compile(rf"\n|[ {MARK}]+[^ {MARK}\n]*|[^ {MARK}\n]+")
        self.line = struct.pack(f"<{len(x := self.model.encode(chr(10)))}I", *x)
        self.table: dict[str, bytes] = {}
        self.most = cached
        pieces = (self.model.id_to_piece(i) for i in range(self.model.get_piece_size()))
        self.chunked = not any(MARK in p.lstrip(MARK) or "\n" in p for p in pieces)
        self.chunked = self.chunked and all(self.encode([t])[0] == self._whole(t) for t in PROBES)

    def _whole(self, text: str) -> bytes:
        ids = self.model.encode(text)
        return struct.pack(f"<{len(ids)}I", *ids)

    def _segment(self, chunks: list[str]) -> list[bytes]:
        """Ids of chunks.  The model puts a marker before every input: a chunk that begins with one gives it up, any other is set behind a line end."""
        marked = [c[1:] if c[0] in (" ", MARK) else "\n" + c for c in chunks]
        found = []
        for c, ids in zip(chunks, self.model.encode(marked, num_threads=1)):
            packed = struct.pack(f"<{len(ids)}I", *ids)
            found.append(packed if c[0] in (" ", MARK) else packed[len(self.line) :])
        return found

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text without begin and end, as little-endian 32-bit integers."""
        if not self.chunked:
            return [self._whole(t) for t in texts]
        parts = [self.chunk.findall(" " + t) if t else [] for t in texts]
        here = {"\n": self.line[4:], " ": self.line[:4], MARK: self.line[:4]}
        new = list({c for p in parts for c in p}.difference(self.table, here))
        here.update(zip(new, self._segment(new)))
        table = self.table
        if len(table) < self.most:
            table.update(here)
        return [b"".join([table[c] if c in table else here[c] for c in p]) for p in parts]


_CODECS: dict[str, ChunkCodec] = {}


def codec(path: str) -> ChunkCodec:
    if path not in _CODECS:
        _CODECS[path] = ChunkCodec(path)
    return _CODECS[path]


def encode_decode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", rows: int = 256) -> DataFrame:
    """Per document: ids (with begin and end) as packed 32-bit integers, their number, and the decoded text.

    Null or empty text: begin and end alone, decoded to the empty text.  Repeated rows and ids are encoded each on its
    own, texts whole whatever their length; an empty table gives no rows; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(model_path)
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                packed = [c.ends[0] + ids + c.ends[1] for ids in c.encode(part.column(1).to_pylist())]
                decoded = [c.model.decode(list(memoryview(p).cast("I"))) for p in packed]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(p) // 4 for p in packed], pa.int64()), pa.array(packed, pa.binary()), pa.array(decoded, pa.string())], names=["doc_id", "n_tokens", "ids", "decoded"])

    return id_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_tokens long, ids binary, decoded string")


def codec_digest(docs: DataFrame, model_path: str) -> DataFrame:
    """SHA-256 of the packed ids and of the decoded text, in lowercase hex."""
    return encode_decode(docs, model_path).select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))
