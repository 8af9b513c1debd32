"""Byte-level BPE with a hierarchical-bitmap rank queue.

Each merge rank has a bucket of positions in a linked list of tokens. Three levels of bitmaps with 64 bits a
word say which buckets hold anything; find-first-set walks them down to the lowest rank. An entry whose pair has changed
since it was queued is stale and skipped. A merge costs constant work besides the bucket's own order, so that
pre-tokens of many thousands of bytes take time in proportion to their length.
"""

from __future__ import annotations

import base64
import sys
import uuid
from array import array
from heapq import heappop, heappush

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.llm.arrow import map_rows
from spurline.llm.pretokens import LOOSE_SPACE, Memo, cuts_at_spaces

#: Bytes of pre-tokens, and of space-separated chunks, whose ids a worker remembers.
REMEMBER = 128 << 20
_NONE = 1 << 40
_WORKER: dict = {}


class RankQueue:
    """Positions by rank: ``push``, and ``pop`` of the least rank's least position."""

    def __init__(self, ranks: int):
        words = -(-ranks // 64)
        self.low, self.mid, self.top = [0] * words, [0] * -(-words // 64), 0
        self.buckets: dict[int, list[int]] = {}

    def push(self, rank: int, position: int) -> None:
        buckets = self.buckets
        if rank in buckets:  # one position stands alone, several are a heap
            bucket = buckets[rank]
            if bucket.__class__ is int:
                buckets[rank] = [bucket, position] if bucket < position else [position, bucket]
            else:
                heappush(bucket, position)
            return
        buckets[rank] = position
        a = rank >> 6
        if not self.low[a]:
            b = rank >> 12
            self.mid[b] |= 1 << (a & 63)
            self.top |= 1 << b
        self.low[a] |= 1 << (rank & 63)

    def pop(self) -> tuple[int, int] | None:
        top = self.top
        if not top:
            return None
        b = (top & -top).bit_length() - 1
        m = self.mid[b]
        a = (b << 6) + (m & -m).bit_length() - 1
        w = self.low[a]
        rank = (a << 6) + (w & -w).bit_length() - 1
        bucket = self.buckets[rank]
        if bucket.__class__ is not int:
            position = heappop(bucket)
            if bucket:
                return rank, position
        else:
            position = bucket
        del self.buckets[rank]
        self.low[a] = w = w & (w - 1)
        if not w:
            self.mid[b] = m = m & (m - 1)
            if not m:
                self.top = top & (top - 1)
        return rank, position


def _pack(ids: list[int]) -> bytes:
    out = array("I", ids)
    if sys.byteorder == "big":
        out.byteswap()
    return out.tobytes()


class Codec:
    """Encoding and decoding by a rank table; ids are ranks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks, self.split = ranks, regex.compile(pattern).findall
        self.bytes = {i: b for b, i in ranks.items()}
        self.queue = RankQueue(max(ranks.values(), default=0) + 1)
        self.words, self.chunks = Memo(REMEMBER), Memo(REMEMBER)
        self.cuts = cuts_at_spaces(pattern)

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one pre-token. Only pairs of lower rank than both neighbours are queued: no other can be next, as a
        merge beside it changes it first. Of equal neighbours the left one is queued."""
        ranks = self.ranks
        if (whole := ranks.get(piece)) is not None:
            return [whole]
        n = len(piece)
        end = list(range(1, n + 1))  # of the token that starts at a position
        before = list(range(-1, n))  # start of the token before it
        pair = [ranks.get(piece[i : i + 2], _NONE) for i in range(n)]  # rank of the token with the one after it
        pair[-1] = _NONE
        push, pop = self.queue.push, self.queue.pop
        queued = [_NONE] * n  # the rank with which a position was queued last
        left = _NONE
        for i in range(n - 1):
            r = pair[i]
            if r < left and r <= pair[i + 1]:
                push(r, i)
                queued[i] = r
            left = r
        while (got := pop()) is not None:
            rank, i = got
            if pair[i] != rank:
                continue
            j = end[i]
            e = end[i] = end[j]
            pair[j] = _NONE
            p = before[i]
            # The two pairs that hold the new token change; they and their neighbours may now be lower than both sides.
            right = _NONE
            if e < n:
                before[e] = i
                pair[i] = own = ranks.get(piece[i : end[e]], _NONE)
                right = pair[e]
                if right < own and right != queued[e] and (end[e] == n or right <= pair[end[e]]):
                    push(right, e)
                    queued[e] = right
            else:
                pair[i] = own = _NONE
            if p >= 0:
                pair[p] = left = ranks.get(piece[p:e], _NONE)
                q = before[p]
                if q >= 0:
                    far = pair[q]
                    if left < far and left <= own:
                        push(left, p)
                    elif far <= left and far < _NONE and far != queued[q] and (before[q] < 0 or far < pair[before[q]]):
                        push(far, q)
                        queued[q] = far
                elif left <= own and left < _NONE:
                    push(left, p)
                if own < left and own <= right:
                    push(own, i)
            elif own <= right and own < _NONE:
                push(own, i)
        out, i = [], 0
        while i < n:
            out.append(ranks[piece[i : end[i]]])
            i = end[i]
        return out

    def _word(self, word: str) -> bytes:
        return self.words.keep(word, _pack(self.merge(word.encode("utf-8"))))

    def _pieces(self, text: str) -> bytes:
        known, make = self.words.get, self._word
        return b"".join([known(w) or make(w) for w in self.split(text)])

    def _chunk(self, chunk: str) -> bytes:
        """A chunk after its space. Letters alone are one pre-token, and so is one common mark after them."""
        if chunk.isalpha():
            ids = _pack(self.merge((" " + chunk).encode("utf-8")))
        elif chunk[-1] in ".,;:!?" and chunk[:-1].isalpha():
            return (self.chunks.get(chunk[:-1]) or self._chunk(chunk[:-1])) + (self.words.get(chunk[-1]) or self._word(chunk[-1]))
        else:
            ids = self._pieces(" " + chunk)
        return self.chunks.keep(chunk, ids)

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers. Under the public pattern each chunk between spaces before visible characters
        stands alone; under any other the text is split as a whole."""
        text = text or ""
        if len(text) < 2 or not self.cuts or LOOSE_SPACE.search(text):
            return self._pieces(text)
        head, *rest = text.split(" ")
        known, make = self.chunks.get, self._chunk
        return b"".join([self._pieces(head), *[known(c) or make(c) for c in rest]])

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def read_ranks(path: str) -> dict[bytes, int]:
    """A rank file: base64 of the bytes, and the rank, on each line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f) if a}


def code_documents(docs: DataFrame, ranks: dict[bytes, int], pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n_tokens, ids, decoded)`` for every row: ids as little-endian unsigned 32-bit integers, and the bytes
    that decoding them gives, which are the text's UTF-8.

    Null text: empty, no ids. Null ids and repeated rows stay as they are. Other columns are ignored.
    """
    if sum(map(len, ranks)) > 64 << 20:
        raise ValueError("a vocabulary of over 64 MB is not broadcast")
    sent, key = docs.sparkSession.sparkContext.broadcast(ranks), uuid.uuid4().hex

    def make():
        if key not in _WORKER:
            _WORKER.clear()
            _WORKER[key] = Codec(sent.value, pattern)
        codec = _WORKER[key]

        def step(doc, text):
            ids = codec.encode(text)
            yield doc, len(ids) // 4, ids, codec.decode(ids)

        return step

    return map_rows(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), ["doc_id", "text"], make, "doc_id long, n_tokens long, ids binary, decoded binary")
