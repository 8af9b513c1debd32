"""Concatenate and cut: two-pass prefix sums give every token a global offset, fixed windows cut there.

Pass 1 tokenizes each partition once, stamps every row with its place inside the partition and writes the
ids. The partitions' totals (one number for each) are summed up, which gives each partition its base. Pass 2
reads the ids again and cuts them at the multiples of the window length. Nothing is shuffled.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.llm.pretokens import LOOSE_SPACE, Memo, cuts_at_spaces
from spurline.runtime import materialise

#: Bytes of space-separated chunks whose ids a worker remembers.
CHUNKS = 160 << 20
_WORKER: dict = {}


def byte_letters() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: each letter's byte."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class WholeTextEncoder:
    """Ids of byte-level BPE in the JSON vocabulary, as little-endian bytes, equal to the tokenizers library's.

    A space before a visible character always starts a new pre-token, so the text between two such spaces can
    be encoded alone and remembered. Texts with other runs of white space are encoded whole, and texts that hold
    an added token's string are left to the library itself.
    """

    def __init__(self, source: str, pattern: str, end_id: int):
        import tiktoken
        from tokenizers import Tokenizer

        if not cuts_at_spaces(pattern):
            raise ValueError("the JSON vocabulary is split by the public pattern only")
        spec, letters = json.loads(source), byte_letters()
        self.library = Tokenizer.from_str(source)
        self.added = [t["content"] for t in spec.get("added_tokens", [])]
        ranks = {bytes(letters[c] for c in word): i for word, i in spec["model"]["vocab"].items() if word not in self.added}
        self.whole = tiktoken.Encoding("vocabulary", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.kind = np.dtype("<u2" if max(*spec["model"]["vocab"].values(), end_id) < 1 << 16 else "<u4")
        self.chunks = Memo(CHUNKS)
        self.end = self._pack([end_id])

    def _pack(self, ids: list[int]) -> bytes:
        return np.array(ids, self.kind).tobytes()

    def _chunk(self, chunk: str) -> bytes:
        return self.chunks.keep(chunk, self._pack(self.whole(" " + chunk)))

    def __call__(self, text: str | None) -> bytes:
        text = text or ""
        if any(x in text for x in self.added):
            return self._pack(self.library.encode(text, add_special_tokens=False).ids) + self.end
        if len(text) < 2 or LOOSE_SPACE.search(text):
            return self._pack(self.whole(text)) + self.end
        head, *rest = text.split(" ")
        known, make = self.chunks.get, self._chunk
        return b"".join([self._pack(self.whole(head)), *[known(c) or make(c) for c in rest], self.end])


def token_table(docs: DataFrame, source: str, pattern: str, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pass 1, written: ``(part, start, n, doc_id, ids)`` with ``start`` counted inside the partition."""
    if len(source) > 64 << 20:
        raise ValueError("a vocabulary of over 64 MB is not broadcast")
    sent, key = docs.sparkSession.sparkContext.broadcast(source), (uuid.uuid4().hex, end_id)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        if key not in _WORKER:
            _WORKER.clear()
            _WORKER[key] = WholeTextEncoder(sent.value, pattern, end_id)
        encode, part, at = _WORKER[key], TaskContext.get().partitionId(), 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                piece = batch.slice(lo, 512)
                ids = [encode(t) for t in piece.column(1).to_pylist()]
                n = np.array([len(x) for x in ids], np.int64) // encode.kind.itemsize
                starts = at + np.concatenate([[0], np.cumsum(n)[:-1]])
                at += int(n.sum())
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), part, np.int32)), pa.array(starts), pa.array(n), piece.column(0), pa.array(ids, pa.binary())], names=["part", "start", "n", "doc_id", "ids"])

    return materialise(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "part int, start long, n long, doc_id long, ids binary"), "tokens")


def pack(tokens: DataFrame, window: int = 2048) -> DataFrame:
    """Pass 2: ``(doc_id, start, length, doc_tokens, sequence_id, offset, continues, ids)``, a row for each piece.

    ``ids`` are little-endian unsigned 32-bit integers. ``continues`` marks boundary records: pieces whose document
    started in an earlier window. All windows but the very last one are full. The totals of the partitions, one number
    each, are all that the driver sees.
    """
    totals = {r.part: r.n for r in tokens.groupBy("part").agg(F.sum("n").alias("n")).collect()}
    parts = sorted(totals)
    base = dict(zip(parts, accumulate((totals[p] for p in parts), initial=0), strict=False))
    sent = tokens.sparkSession.sparkContext.broadcast(base)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                piece, out = batch.slice(lo, 512), []
                for part, start, n, doc, raw in zip(*(c.to_pylist() for c in piece.columns), strict=True):
                    ids = np.frombuffer(raw, "<u2" if len(raw) == 2 * n else "<u4").astype("<u4")
                    first = sent.value[part] + start
                    done = 0
                    while done < n:
                        seq, off = divmod(first + done, window)
                        take = min(n - done, window - off)
                        out.append((doc, done, take, n, seq, off, done > 0, ids[done : done + take].tobytes()))
                        done += take
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), KINDS, strict=True)], names=NAMES)

    return tokens.select("part", "start", "n", "doc_id", "ids").mapInArrow(run, "doc_id long, start long, length long, doc_tokens long, sequence_id long, offset long, continues boolean, ids binary")


NAMES = ["doc_id", "start", "length", "doc_tokens", "sequence_id", "offset", "continues", "ids"]
KINDS = [*[pa.int64()] * 6, pa.bool_(), pa.binary()]


def pack_documents(docs: DataFrame, vocabulary: str | None = None, pattern: str | None = None, window: int = 2048, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All ``docs`` as pieces of windows; see :func:`pack`.

    ``vocabulary`` is the path of a byte-level BPE in the tokenizers library's JSON format, read on the driver.
    Null text: empty, so the document is the end id alone. Null ids and repeated rows are packed like others. An empty
    table gives no pieces. Other columns are ignored.
    """
    import public_tokenizers

    with open(vocabulary or public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        source = f.read()
    return pack(token_table(docs, source, pattern or public_tokenizers.PATTERN, end_id, id_col, text_col), window)
