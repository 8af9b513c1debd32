"""Quality by a factorisation machine over hashed words, structure statistics and metadata.

Pairwise interactions have low rank and are scored in linear time:
sum over i<j of <v_i, v_j> x_i x_j = 1/2 sum over f of ((sum_i v_if x_i)^2 - sum_i v_if^2 x_i^2).
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.llm.arrow import map_rows
from spurline.llm.pretokens import Memo

HASHED = 1 << 14
STATS = 13
#: Labelled rows that the model is fitted on, at most: those with the least hashes of their ids.
TRAIN_ROWS = 6_000
_SYMBOLS = "#*$%&|<>"
#: Bytes of words whose places a worker remembers.
_words = Memo(96 << 20)


def _word_index(word: str) -> int:
    return _words.keep(word, STATS + zlib.crc32(word.encode("utf-8", "surrogatepass")) % HASHED)


def features(text: str | None, n_chars: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sparse features: statistics first, then hashed words with unit length in all. Null text: empty."""
    text = text or ""
    words = text.split()
    n, size = max(1, len(words)), max(1, len(text))
    lines = [x for x in text.split("\n") if x.strip()]
    counts = Counter(words)
    stats = [
        sum(map(str.isupper, words)) / n,
        min(1.0, 10 * sum(map(text.count, _SYMBOLS)) / size),
        min(1.0, text.count("|") / n),
        min(1.0, text.count("!!") / n),
        1 - len(counts) / n,
        max(counts.values(), default=0) / n,
        1 - len(set(lines)) / max(1, len(lines)),
        min(1.0, size / n / 20),
        sum(x.rstrip()[-1] in ".!?:;\"')" for x in lines) / max(1, len(lines)),
        math.log1p(len(text)) / 12,
        math.log1p(len(lines)) / 8,
        float(not words),
        math.log1p(max(0, len(text) if n_chars is None else n_chars)) / 12,  # metadata
    ]
    known = _words.get
    at = np.fromiter((known(w) or _word_index(w) for w in counts), np.int32, len(counts))
    value = np.log1p(np.fromiter(counts.values(), np.float32, len(counts)))
    value /= max(1e-9, float(np.sqrt((value**2).sum())))
    return np.concatenate([np.arange(STATS, dtype=np.int32), at]), np.concatenate([np.array(stats, np.float32), value])


@dataclass
class FactorisationMachine:
    bias: float
    w: np.ndarray
    v: np.ndarray

    @classmethod
    def empty(cls, rank: int = 4, seed: int = 7) -> FactorisationMachine:
        return cls(0.0, np.zeros(STATS + HASHED, np.float32), np.random.default_rng(seed).normal(0, 0.02, (STATS + HASHED, rank)).astype(np.float32))

    def raw(self, rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        at, x = np.concatenate([r[0] for r in rows]), np.concatenate([r[1] for r in rows])
        first = np.concatenate([[0], np.cumsum([len(r[0]) for r in rows])[:-1]])
        vx = self.v[at] * x[:, None]
        s, q = np.add.reduceat(vx, first), np.add.reduceat(vx * vx, first)
        return self.bias + np.add.reduceat(self.w[at] * x, first) + 0.5 * (s * s - q).sum(1)

    def scores(self, rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(rows).astype(np.float64), -30, 30)))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, rounds: int = 12, step: float = 0.1, decay: float = 1e-4, seed: int = 7) -> FactorisationMachine:
        """Logistic loss, adaptive steps; rows and their order are all that it depends on."""
        rng, gw, gv, gb = np.random.default_rng(seed), np.full_like(self.w, 1e-6), np.full_like(self.v, 1e-6), 1e-6
        for _ in range(rounds):
            order = rng.permutation(len(rows))
            for lo in range(0, len(order), 128):
                pick = order[lo : lo + 128]
                part = [rows[i] for i in pick]
                at, x = np.concatenate([r[0] for r in part]), np.concatenate([r[1] for r in part])
                size = np.array([len(r[0]) for r in part])
                first = np.concatenate([[0], np.cumsum(size)[:-1]])
                vx = self.v[at] * x[:, None]
                s = np.add.reduceat(vx, first)
                err = (1 / (1 + np.exp(-np.clip(self.bias + np.add.reduceat(self.w[at] * x, first) + 0.5 * (s * s - np.add.reduceat(vx * vx, first)).sum(1), -30, 30))) - y[pick]).astype(np.float32) / len(pick)
                e = np.repeat(err, size) * x
                used, back = np.unique(at, return_inverse=True)
                dw = np.bincount(back, e, len(used)).astype(np.float32) + decay * self.w[used]
                each = e[:, None] * (np.repeat(s, size, axis=0) - vx)
                dv = np.stack([np.bincount(back, each[:, f], len(used)) for f in range(each.shape[1])], 1).astype(np.float32) + decay * self.v[used]
                gw[used] += dw * dw
                gv[used] += dv * dv
                gb += float(err.sum()) ** 2
                self.w[used] -= step * dw / np.sqrt(gw[used])
                self.v[used] -= step * dv / np.sqrt(gv[used])
                self.bias -= step * float(err.sum()) / math.sqrt(gb)
        return self


def held_out(id_col: str = "doc_id") -> F.Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def _inputs(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    n = F.col("n_chars").cast("long") if "n_chars" in docs.columns else F.lit(None).cast("long")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), n.alias("n_chars"))


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, id_col: str = "doc_id", text_col: str = "text", rank: int = 4) -> FactorisationMachine | None:
    """Fit on at most ``rows`` labelled documents outside the held-out fifth; None if there are none.

    Rows of ``labels`` with a null id or null quality are ignored; of repeated labels the lower quality counts. Of documents
    with one id only one row is learnt from.
    """
    named = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.min(F.col("quality").cast("int")).alias("y"))
    chosen = named.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)  # bounded by rows, so it may be broadcast

    def make():
        def step(doc, text, n_chars, y):
            at, x = features(text, n_chars)
            yield doc, y, at.tobytes(), x.tobytes()

        return step

    found = map_rows(_inputs(docs, id_col, text_col).join(F.broadcast(chosen), "doc_id"), ["doc_id", "text", "n_chars", "y"], make, "doc_id long, y int, at binary, x binary")
    got = sorted(found.groupBy("doc_id").agg(F.min(F.struct("y", "at", "x")).alias("r")).collect(), key=lambda r: r.doc_id)
    if not got:
        return None
    data = [(np.frombuffer(r.r.at, np.int32), np.frombuffer(r.r.x, np.float32)) for r in got]
    return FactorisationMachine.empty(rank).fit(data, np.array([r.r.y for r in got], np.float32))


def _scorer(spark, model: FactorisationMachine | None):
    sent = spark.sparkContext.broadcast(model)  # a fixed size: (rank + 1) * (HASHED + STATS) numbers

    def score(texts: pa.Array, sizes: pa.Array | None) -> np.ndarray:
        n = sizes.to_pylist() if sizes is not None else [None] * len(texts)
        if sent.value is None:
            return np.full(len(texts), 0.5)
        return sent.value.scores([features(t, k) for t, k in zip(texts.to_pylist(), n, strict=True)]) if len(texts) else np.empty(0)

    return score


def score_documents(docs: DataFrame, model: FactorisationMachine | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, score)`` for every row: 0 to 1, higher if good quality is likelier; 0.5 everywhere without a model.

    Null and empty texts are scored as texts without words. Null ids and repeated rows stay. Other columns than the text
    and ``n_chars`` have no influence.
    """
    score = _scorer(docs.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(score(part.column(1), part.column(2)))], names=["doc_id", "score"])

    return _inputs(docs, id_col, text_col).mapInArrow(run, "doc_id long, score double")


def keep_good(docs: DataFrame, model: FactorisationMachine | None, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` that score at least ``threshold``, unchanged and with all their columns."""
    score, names = _scorer(docs.sparkSession, model), docs.columns
    text, size = names.index("text"), names.index("n_chars") if "n_chars" in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                yield part.filter(pa.array(score(part.column(text), None if size is None else part.column(size)) >= threshold))

    return docs.mapInArrow(run, docs.schema)
