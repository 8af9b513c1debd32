"""Near duplicates by SimHash, with pigeonring filtering of the candidates.

A fingerprint has 64 bits, seen as a ring of five segments. If two fingerprints differ in at most three
bits, some start segment exists from which every chain of l consecutive segments (l = 1..5) differs in at
most floor(3 l / 5) bits: 0, 1, 1, 2, 3. Hence the start segment is equal, and of the next two at most one
bit differs, so one of them is equal as well. Ten exact keys of 25 or 26 bits therefore find every such pair.
Within a key's bucket the chain budgets are tested before the full Hamming distance. A bucket with too many fingerprints is
split by the next segments of the chain, whose budgets say how many bits they may differ in.
"""

from __future__ import annotations

from collections.abc import Iterator

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spurline.llm.arrow import map_rows
from spurline.operators.components import components
from spurline.runtime import materialise

WIDTHS = (13, 13, 13, 13, 12)
SHIFTS = tuple(64 - sum(WIDTHS[: i + 1]) for i in range(5))
MAX_BITS = 3
#: Distinct fingerprints that a bucket may have before it is split by another segment.
BUCKET = 16_384
#: Rows of one fingerprint above which it is hot: at least so many, and at least this share of all rows.
HOT_ROWS, HOT_SHARE = 64, 1e-4


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """SimHash (signed 64 bits) of word shingles, repeats included; no words: zero."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII only, both for case and white space
    if not words:
        return 0
    if len(words) < shingle:
        grams = [b" ".join(words)]
    else:
        grams = list(map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False)))
    digest, ones, total = xxhash.xxh64_intdigest, np.zeros(64, np.int64), len(grams)
    for at in range(0, total, 65_536):
        h = np.array([digest(g, 42) for g in grams[at : at + 65_536]], dtype=">u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > total).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp)`` for every row; a null text counts as empty."""
    def make():
        return lambda i, t: ((i, fingerprint(t)),)

    return map_rows(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), ["doc_id", "text"], make, "doc_id long, fp long")


def _segment(fp: F.Column, at: F.Column) -> F.Column:
    """The segment with the number ``at`` (0..4) of a fingerprint."""
    out = F
    for i, (shift, w) in enumerate(zip(SHIFTS, WIDTHS, strict=True)):
        out = out.when(at == i, F.shiftrightunsigned(fp, shift).bitwiseAND(F.lit((1 << w) - 1)))
    return out


def ring_keys(fps: DataFrame) -> DataFrame:
    """``(start, second, value, fp, own)``: the ten bucket keys of each fingerprint: the start segment and one of the next two are equal."""
    seg = [F.shiftrightunsigned("fp", s).bitwiseAND(F.lit((1 << w) - 1)) for s, w in zip(SHIFTS, WIDTHS, strict=True)]
    keys = [F.struct(F.lit(i).alias("start"), F.lit(j).alias("second"), F.shiftleft(seg[i], 13).bitwiseOR(seg[(i + j) % 5]).alias("value")) for i in range(5) for j in (1, 2)]
    return fps.select(F.explode(F.array(*keys)).alias("k"), "fp").select("k.*", "fp", F.lit(True).alias("own"))


def split_keys(rows: DataFrame, place: F.Column, bits: int) -> DataFrame:
    """``rows`` of overfull buckets under finer keys: the segment ``place`` steps from the start joins the key, under every value
    that differs from the fingerprint's in at most ``bits`` bits. ``own`` marks a fingerprint under its own value, so any two that
    may be linked meet where one of them is at home."""
    flips = [0, *(sum(1 << b for b in c) for n in range(1, bits + 1) for c in combinations(range(13), n))]
    at = F.pmod(F.col("start") + place, F.lit(5))
    width = F.when(at == 4, WIDTHS[4]).otherwise(WIDTHS[0])
    rows = rows.withColumn("seg", _segment(F.col("fp"), at)).withColumn("width", width).withColumn("flip", F.explode(F.array(*map(F.lit, flips))))
    rows = rows.where(F.expr("flip < shiftleft(1, width)"))
    return rows.select("start", "second", F.shiftleft("value", 13).bitwiseOR(F.col("seg").bitwiseXOR(F.col("flip").cast("long"))).alias("value"), "fp", (F.col("own") & (F.col("flip") == 0)).alias("own"))


def _linked(x: np.ndarray, start: np.ndarray | int) -> np.ndarray:
    """Which differences x (uint64) keep all chain budgets from ``start`` and the whole distance."""
    masks = np.array([((1 << w) - 1) << s for s, w in zip(SHIFTS, WIDTHS, strict=True)], dtype=np.uint64)
    run = np.zeros(x.shape, np.int64)
    ok = np.ones(x.shape, bool)
    for n in range(1, 6):
        run += np.bitwise_count(x & masks[(np.asarray(start) + n - 1) % 5])
        ok &= run <= MAX_BITS * n // 5
    return ok


def _forest(f: np.ndarray, start: int, own: int) -> list[tuple[int, int]]:
    """Spanning links (positions) of one bucket, from the first ``own`` fingerprints, which are at home in it; never all its pairs."""
    links, left = [], np.arange(len(f))
    while len(left) and left[0] < own:
        todo, left = [left[0]], left[1:]
        while todo and len(left):
            a = todo.pop()
            hit = _linked(f[left] ^ f[a], start)
            if hit.any():
                todo.extend(new := left[hit])
                links.extend((a, b) for b in new)
                left = left[~hit]
    return links


def _bucket_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (start, second, value, guest, fp), sorted, to links; a bucket may cross batches."""
    keep = [np.empty(0, np.int64)] * 4

    def links(start: np.ndarray, key: np.ndarray, guest: np.ndarray, f: np.ndarray) -> pa.RecordBatch:
        cut = np.flatnonzero(np.diff(key)) + 1
        first, last = np.concatenate([[0], cut]), np.concatenate([cut, [len(key)]])
        size, g = last - first, f.view(np.uint64)
        two = first[size == 2]
        two = two[_linked(g[two] ^ g[two + 1], start[two])]
        us, vs = [f[two]], [f[two + 1]]
        for a, b in zip(first[size > 2], last[size > 2], strict=True):
            if found := _forest(g[a:b], int(start[a]), int(b - a - guest[a:b].sum())):
                pairs = np.array(found)
                us.append(f[a + pairs[:, 0]])
                vs.append(f[a + pairs[:, 1]])
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], names=["u", "v"])

    for batch in batches:
        start, second, value, guest, fp = (batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(5))
        new = (start, (start * 2 + second - 1) << 52 | value, guest, fp)  # a value has 52 bits at most
        start, key, guest, fp = (np.concatenate([a, b]) for a, b in zip(keep, new, strict=True))
        if not len(key):
            continue
        at = int(np.flatnonzero(key == key[-1])[0])
        keep = [a[at:] for a in (start, key, guest, fp)]
        if at:
            yield links(start[:at], key[:at], guest[:at], fp[:at])
    if len(keep[1]):
        yield links(*keep)


def near_links(fps: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """``(u, v)``: links that join any two distinct fingerprints within three bits, directly or through others
    within three bits of each other. ``fps`` has distinct ``fp``.

    A bucket of over ``bucket`` fingerprints is split by the remaining one of the two segments after the start (the chain of three
    allows one bit in all, so it differs in one bit at most), and one still overfull by the fourth segment (two bits). Four equal
    segments leave 12 or 13 bits, so that at most 8,192 fingerprints are at home in such a bucket.
    """
    key = ["start", "second", "value"]
    rows, parts = ring_keys(fps), []
    for place, bits in ((3 - F.col("second"), 1), (F.lit(3), 2)):
        full = materialise(rows.where("own").groupBy(*key).count().where(F.col("count") > bucket).select(*key), "overfull")
        if full.isEmpty():
            break
        parts.append(rows.join(full, key, "left_anti"))
        rows = split_keys(rows.join(full, key, "left_semi"), place, bits)
    parts.append(rows)
    out = None
    for part in parts:
        found = part.withColumn("guest", ~F.col("own")).repartition(*key).sortWithinPartitions(*key, "guest", "fp").select(*key, "guest", "fp").mapInArrow(_bucket_links, "u long, v long")
        out = found if out is None else out.unionByName(found)
    return out.distinct()


def near_groups(rows: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """``rows`` (``fp, doc_id`` and more, written before) with ``component_id``, the least id of all rows that links reach, and ``root``,
    the least fingerprint of them.

    Rows of hot fingerprints, which a third of all may share, take their group from a broadcast table; at most 10,000
    fingerprints can be hot. All other rows meet theirs in a shuffle.
    """
    reps = materialise(rows.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n")), "prints")
    found = components(near_links(reps.select("fp"), bucket)).select(F.col("id").alias("fp"), F.col("component").alias("root"))
    linked = materialise(found.join(reps.select("fp", "rep"), "fp"), "linked")
    least = linked.groupBy("root").agg(F.min("rep").alias("component_id"))
    moved = linked.select("fp", "root").join(least, "root")
    ids = materialise(reps.join(moved, "fp", "left").select("fp", "n", F.coalesce("component_id", "rep").alias("component_id"), F.coalesce("root", "fp").alias("root")), "groups")
    total = reps.agg(F.sum("n")).first()[0] or 0
    hot = F.col("n") > max(HOT_ROWS, HOT_SHARE * total)
    placed = rows.join(F.broadcast(ids.where(hot).select("fp", F.struct("component_id", "root").alias("hot"))), "fp", "left")
    usual = placed.where("hot is null").drop("hot").join(ids.where(~hot).select("fp", "component_id", "root"), "fp")
    return placed.where("hot is not null").select("*", "hot.component_id", "hot.root").drop("hot").unionByName(usual)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket: int = BUCKET) -> DataFrame:
    """``(doc_id, fp, component_id)`` for every row of ``docs``.

    Equal fingerprints are grouped first, so copies cost one row however many there are; only one
    representative of each fingerprint goes on. ``component_id`` is the least id of all rows that can be
    reached through links of at most three bits. Null text: empty, fingerprint zero, linked like any other.
    A null id never becomes a component id unless a group has no other. Repeated rows give repeated rows.
    An empty table gives an empty result. Other columns of ``docs`` are ignored.
    """
    return near_groups(materialise(fingerprints(docs, id_col, text_col), "fingerprints"), bucket).select("doc_id", "fp", "component_id")


def _fresh(name: str, taken: list[str]) -> str:
    while name.lower() in {t.lower() for t in taken}:
        name += "_"
    return name


def drop_near_duplicates(docs: DataFrame) -> DataFrame:
    """``docs`` with one document of each near-duplicate group: the one with the least ``doc_id``, nulls last; where rows of that id
    differ in their text, the one with the least digest of it; of rows equal in both the least by the other columns.

    Groups are chosen among ids, fingerprints and digests; texts are shuffled once, by the digests that stay.
    An empty table stays empty. ``docs`` needs ``doc_id`` and ``text``; other columns may have any name.
    """
    id_, text = F.col("doc_id").cast("long"), F.col("text").cast("string")
    key = F.md5(F.concat_ws(":", F.coalesce(id_.cast("string"), F.lit("")), text.isNull().cast("string"), F.coalesce(text, F.lit(""))))

    def make():
        return lambda i, t, k: ((i, fingerprint(t), k),)

    narrow = map_rows(docs.select(id_.alias("doc_id"), text.alias("text"), key.alias("row_key")), ["doc_id", "text", "row_key"], make, "doc_id long, fp long, row_key string")
    groups = near_groups(materialise(narrow, "fingerprints"))
    keep = groups.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id"), F.col("row_key"))).alias("r")).select("r.row_key").distinct()
    mark, place = _fresh("row_key", docs.columns), _fresh("place", docs.columns)
    kept = docs.withColumn(mark, key).join(keep.withColumnRenamed("row_key", mark), mark, "left_semi")
    order = [c for c in docs.columns if "map<" not in dict(docs.dtypes)[c] and "variant" not in dict(docs.dtypes)[c]]
    return kept.withColumn(place, F.row_number().over(Window.partitionBy(mark).orderBy(*[F.col(f"`{c}`") for c in order]))).where(F.col(place) == 1).select(*[F.col(f"`{c}`") for c in docs.columns])
