"""Secret scans: patterns find candidates, a random forest drops the false ones.

The forest looks at a candidate's length, its character transitions and entropy, how much of it dictionary words cover,
the path it stands in and the words beside it. It is trained from labelled findings. Every step takes time in proportion to the
text: patterns have no part that is tried again from each position, and overlaps are settled by merging sorted spans.
"""

from __future__ import annotations

import hashlib
import json
import math
import random
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from operator import ne

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.llm.arrow import map_rows

#: Published key formats.
FORMATS = {
    "aws_key": r"\bA(?:KI|SI)A[0-9A-Z]{16}\b",
    "github": r"\bgh[pousr]_[0-9A-Za-z]{36,}+\b",
    "slack": r"\bxox[abprs]-[0-9A-Za-z-]{10,}+",
    "google_key": r"\bAIza[0-9A-Za-z_-]{35}",
    "jwt": r"(?<![0-9A-Za-z_-])eyJ[0-9A-Za-z_-]{8,}+\.[0-9A-Za-z_-]{8,}+\.[0-9A-Za-z_-]*+",
    "private_key": r"-----BEGIN [A-Z ]{0,24}PRIVATE KEY-----(?:[0-9A-Za-z+/=\s]*+-----END [A-Z ]{0,24}PRIVATE KEY-----)?",
}
_known = re.compile("|".join(f"(?P<{k}>{v})" for k, v in FORMATS.items())).finditer
#: A name that says secret, with up to 64 more letters, then an assignment. What stands before the word does not matter.
_ASSIGNED = r"(?:token|secret|passw(?:or)?d|pwd|api[_-]?key|credential|auth|private[_-]?key)[0-9A-Za-z_-]{0,64}+[\"']?\s{0,4}[:=]{1,2}>?\s{0,4}[\"'`]?(?P<value>[^\s\"'`,;<>(){}]{8,}+)"
_assigned, _assigned_any = re.compile(_ASSIGNED).finditer, re.compile(_ASSIGNED, re.IGNORECASE).finditer
_run = re.compile(r"[0-9A-Za-z+/_=-]{24,}+").finditer
#: What a text must hold somewhere for the patterns above to be tried at all.
_ANCHORS, _NAMES = ("AKIA", "ASIA", "ghp_", "gho_", "ghu_", "ghs_", "ghr_", "xox", "AIza", "eyJ", "-----BEGIN "), ("token", "secret", "passw", "pwd", "key", "credential", "auth")
_digit, _letter = re.compile(r"[0-9]").search, re.compile(r"[A-Za-z]").search
_beside = re.compile(r"[a-z]+").findall
_letters = re.compile(r"[a-z]{4,}").findall
_hex = re.compile(r"[0-9a-fA-F]+").fullmatch
_uuid = re.compile(r"[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}").fullmatch
#: Words that speak for and against a finding.
FOR = {"token", "secret", "password", "passwd", "pwd", "key", "apikey", "api", "auth", "credential", "credentials", "bearer", "access", "private", "client"}
AGAINST = {"example", "sample", "dummy", "test", "fake", "placeholder", "changeme", "your", "xxxx", "sha", "md5", "checksum", "digest", "commit", "uuid", "guid", "hash", "revision", "build", "id", "integrity", "etag"}
#: Letters of the least dictionary word (as in _letters), and words beside a candidate that count on each side.
WORD_LETTERS, BESIDE = 4, 3
_test_path = re.compile(r"(?:^|[/_.-])(?:tests?|examples?|samples?|docs?|fixtures?|mocks?)(?:[/_.-]|$)", re.IGNORECASE).search
_CLASSES = bytes(48 if chr(c).isdigit() and c < 128 else 97 if 97 <= c <= 122 else 65 if 65 <= c <= 90 else 46 for c in range(256))
FEATURES = 14


def _without_overlaps(held: list[tuple[int, int, str]], more: Iterable[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """``held`` and those of ``more`` that meet none of it, in order; both are sorted and free of overlaps in themselves."""
    out, at = [], 0
    for x in more:
        while at < len(held) and held[at][1] <= x[0]:
            out.append(held[at])
            at += 1
        if at == len(held) or held[at][0] >= x[1]:
            out.append(x)
    return out + held[at:]


def candidates(text: str) -> list[tuple[int, int, str]]:
    """``(start, end, kind)`` without overlaps, in order; known formats win over assignments, those over long runs with letters and digits."""
    found = [(m.start(), m.end(), m.lastgroup) for m in _known(text)] if any(x in text for x in _ANCHORS) else []
    low = text.lower()  # no shorter than the text; if as long, it has the same positions
    if any(x in low for x in _NAMES):
        found = _without_overlaps(found, ((*m.span("value"), "assigned") for m in (_assigned(low) if len(low) == len(text) else _assigned_any(text))))
    return _without_overlaps(found, ((*m.span(), "run") for m in _run(text) if _digit(m[0]) and _letter(m[0])))


class Words:
    """A dictionary that tells how much of a text its words cover; the automaton is built once in each process."""

    def __init__(self, words: Iterable[str] = ()):
        self.words, self._scan = tuple(words), None

    def __getstate__(self):
        return self.words

    def __setstate__(self, words):
        self.__init__(words)

    def covered(self, text: str) -> int:
        if self._scan is None:
            import ahocorasick

            found = ahocorasick.Automaton()
            for w in self.words:
                found.add_word(w, len(w))
            found.make_automaton()
            self._scan = found.iter_long if self.words else lambda t: ()
        return sum(k for part in _letters(text) for _, k in self._scan(part))


def dictionary(vocabulary: str | None = None) -> Words:
    """The dictionary: words of lower-case ASCII letters in the vocabulary of a byte-level BPE (tokenizers' JSON; read on the
    driver), where a leading space marks the beginning of a word."""
    import public_tokenizers

    with open(vocabulary or public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        tokens = json.load(f)["model"]["vocab"]
    return Words(sorted(t[1:] for t in tokens if t[0] == "\u0120" and len(t) > WORD_LETTERS and t[1:].isascii() and t[1:].isalpha() and t[1:].islower()))


@lru_cache(maxsize=1 << 12)
def _bits(count: int) -> float:
    return count * math.log2(count)


def describe(value: str, before: str, after: str, path: str, kind: str, words: Words) -> list[float]:
    """The features of a candidate."""
    n = max(1, len(value))
    classes = value.encode("latin-1", "replace").translate(_CLASSES)
    counts, low = Counter(value), value.lower()
    covered = words.covered(low)
    beside = {*_beside(before.lower()[-48:])[-BESIDE:], *_beside(after.lower()[:16])[:BESIDE]}
    return [
        min(n, 200),
        sum(map(ne, classes, classes[1:])) / n,
        math.log2(n) - sum(map(_bits, counts.values())) / n,
        classes.count(b"0") / n,
        classes.count(b"A") / n,
        classes.count(b".") / n,
        float(_hex(value) is not None),
        covered / n,
        max(counts.values(), default=0) / n,
        float(bool(_test_path(path))),
        float(not beside.isdisjoint(FOR)),
        float(not beside.isdisjoint(AGAINST) or not AGAINST.isdisjoint(_beside(low[:400]))),
        float(kind not in ("assigned", "run")),
        float(_uuid(value) is not None),
    ]


def labelled_findings(n: int = 3200, seed: int = 11, words: Words | None = None) -> list[tuple[str, str, str, str, str, int]]:
    """``(value, before, after, path, kind, label)``: a fixed, made set of findings with their labels, the default training rows."""
    words = (words or dictionary()).words
    rng, out = random.Random(seed), []
    hexes, mixed, base = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
    some = lambda letters, k: "".join(rng.choices(letters, k=k))
    few = lambda a, b: rng.choices(words, k=rng.randint(a, b))
    uuid = lambda: "-".join(some(hexes, k) for k in (8, 4, 4, 4, 12))
    secret_names = ("token", "secret", "password", "api_key", "auth_token", "client_secret", "access key", "db password", "apikey", "private_key")
    plain_names = ("sha256", "md5", "commit", "uuid", "checksum", "build id", "revision", "digest", "integrity", "etag")
    for i in range(n):
        quote, path = rng.choice(('"', "'", "")), rng.choice(("", "src/app.py", "conf/prod.yml", "main.go", "src7"))
        prose = " ".join(few(0, 5))
        after = quote + rng.choice(("", " ", " " + " ".join(few(1, 3))))
        if i % 2:
            value, kind = rng.choice((
                lambda: (some(hexes, rng.choice((32, 40, 48, 64))), "assigned"), lambda: (some(mixed, rng.randint(12, 64)), "assigned"), lambda: (some(base, rng.choice((40, 44, 64, 88, 400))), rng.choice(("run", "assigned"))), lambda: ("AKIA" + some("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 16), "aws_key"),
                lambda: ("ghp_" + some(mixed, 36), "github"), lambda: ("xoxb-" + some("0123456789", 12) + "-" + some(mixed, 24), "slack"), lambda: ("AIza" + some(mixed + "_-", 35), "google_key"), lambda: (".".join(("eyJ" + some(mixed, 24), some(mixed, 60), some(mixed + "-_", 43))), "jwt"),
                lambda: (some(mixed + "!@#$%^&*", rng.randint(10, 20)), "assigned"), lambda: ("-----BEGIN RSA PRIVATE KEY-----\n" + some(base, 200), "private_key"), lambda: (rng.choice(("sk_live_", "rk_live_", "npm_", "glpat-")) + some(mixed, 24), rng.choice(("run", "assigned")))))()
            name = rng.choice(secret_names) if kind in ("assigned", "run") or rng.random() < 0.4 else rng.choice((*few(1, 1), "see", "use"))
            out.append((value, f"{prose}{rng.choice((' ', ' export ', ' the '))}{name}{rng.choice((' = ', ': ', '='))}{quote}", after, path, kind, 1))
        else:
            value, kind, name = rng.choice((
                lambda: (some(hexes, rng.choice((32, 40, 64))), "run", rng.choice(plain_names)), lambda: (uuid(), "run", rng.choice((*plain_names, "id", *few(1, 1)))), lambda: (rng.choice("_-").join(few(3, 6)) + str(rng.randint(0, 99)), rng.choice(("run", "assigned")), rng.choice((*secret_names, "name", "class"))),
                lambda: (rng.choice(("your_api_key_here", "xxxxxxxxxxxxxxxx", "changeme123", "example-token-0000", "PLACEHOLDER_VALUE_1", "dummy_secret_value", "test1234test1234", "********", "0000000000000000")), "assigned", rng.choice(secret_names)), lambda: ("/".join(few(4, 6)) + "/v2", "run", rng.choice(("path", "import", "see"))),
                lambda: ("AKIA" + some("ABCDEFGHIJKLMNOPQRSTUVWXYZ", 9) + "EXAMPLE", "aws_key", "example"), lambda: (".".join(few(2, 4)), "assigned", rng.choice(secret_names)), lambda: ("".join(w.title() for w in few(4, 6)) + str(rng.randint(2, 9)), "run", rng.choice(("class", "import", "new"))),
                lambda: (rng.choice(("sha512-", "sha256-")) + some(base, rng.choice((43, 86))) + "=", "run", rng.choice(("integrity", "digest"))), lambda: ("".join(few(1, 2)), "assigned", rng.choice(("author", "authority", "token", "password", "passwords")))))()
            out.append((value, f"{prose}{rng.choice((' ', ' the ', ' see '))}{name}{rng.choice((' = ', ': ', ' '))}{quote}", after, rng.choice((path, path, "tests/test_app.py", "docs/example.md")), kind, 0))
    return out


@dataclass
class Forest:
    """Trees as flat arrays: feature (-1: leaf), threshold, left child (right is the next), share of positives."""

    trees: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]
    words: Words = field(default_factory=Words)

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, trees: int = 31, depth: int = 9, leaf: int = 2, seed: int = 5) -> Forest:
        rng, out = np.random.default_rng(seed), []
        tried = max(2, int(math.sqrt(x.shape[1])))
        for _ in range(trees):
            feature, threshold, left, share = [-1], [0.0], [0], [0.0]
            todo = [(0, rng.integers(0, len(y), len(y)), 0)]
            while todo:
                node, rows, level = todo.pop()
                share[node] = float(y[rows].mean())
                if level >= depth or len(rows) < 2 * leaf or share[node] in (0.0, 1.0):
                    continue
                best = (1e-9, None, None)
                own = 2 * share[node] * (1 - share[node])
                for f in rng.permutation(x.shape[1])[:tried]:
                    order = np.argsort(x[rows, f], kind="stable")
                    v, t = x[rows[order], f], np.cumsum(y[rows[order]])
                    cut = np.flatnonzero(v[1:] > v[:-1])
                    cut = cut[(cut + 1 >= leaf) & (len(v) - cut - 1 >= leaf)]
                    if len(cut):
                        n, m = cut + 1, len(v) - cut - 1
                        p, q = t[cut] / n, (t[-1] - t[cut]) / m
                        gain = own - (n * 2 * p * (1 - p) + m * 2 * q * (1 - q)) / len(v)
                        k = int(gain.argmax())
                        if gain[k] > best[0]:
                            best = (float(gain[k]), int(f), float((v[cut[k]] + v[cut[k] + 1]) / 2))
                if best[1] is None:
                    continue
                below = x[rows, best[1]] <= best[2]
                feature[node], threshold[node], left[node] = best[1], best[2], len(feature)
                for part in (rows[below], rows[~below]):
                    todo.append((len(feature), part, level + 1))
                    feature.append(-1), threshold.append(0.0), left.append(0), share.append(0.0)
            out.append(tuple(map(np.array, (feature, threshold, left, share))))
        return cls(out)

    def predict(self, x: np.ndarray) -> np.ndarray:
        total = np.zeros(len(x))
        for feature, threshold, left, share in self.trees:
            node, row = np.zeros(len(x), np.int64), np.arange(len(x))
            while len(row):
                at = node[row]
                inner = feature[at] >= 0
                row, at = row[inner], at[inner]
                node[row] = left[at] + (x[row, feature[at]] > threshold[at])
            total += share[node]
        return total / len(self.trees)


def train_forest(rows: list[tuple[str, str, str, str, str, int]] | None = None, words: Words | None = None) -> Forest:
    """``rows`` as from :func:`labelled_findings`; a bounded list, held on the driver."""
    words = words if words is not None else dictionary()
    rows = rows if rows is not None else labelled_findings(words=words)
    forest = Forest.fit(np.array([describe(*r[:5], words) for r in rows]), np.array([r[5] for r in rows], float))
    forest.words = words
    return forest


def labelled_rows(labelled: DataFrame, rows: int = 20_000) -> list[tuple[str, str, str, str, str, int]]:
    """Training rows from a labelled table (``value, before, after, path, kind, label``): at most ``rows``, those with the least
    hashes. Rows with a null value or label are left out, other nulls count as empty."""
    fields = ["value", "before", "after", "path", "kind"]
    sound = labelled.where("value is not null and label is not null").select(*[F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c) for c in fields], F.col("label").cast("int").alias("label"))
    return [tuple(r) for r in sound.orderBy(F.xxhash64(*fields, "label"), *fields, "label").limit(rows).collect()]


def by_kind(rows: list[tuple[str, str, str, str, str, int]], forest: Forest, threshold: float = 0.5) -> dict[str, tuple[float, float, int]]:
    """Precision, recall and number of true findings of each kind, over labelled findings; ``all`` is over all kinds."""
    said = forest.predict(np.array([describe(*r[:5], forest.words) for r in rows])) >= threshold
    out = {}
    for kind in ("all", *sorted({r[4] for r in rows})):
        at = [(s, r[5]) for s, r in zip(said, rows, strict=True) if kind in ("all", r[4])]
        hit, told, true = sum(s and y for s, y in at), sum(s for s, _ in at), sum(y for _, y in at)
        out[kind] = (hit / told if told else 1.0, hit / true if true else 1.0, true)
    return out


def findings(text: str | None, path: str | None, forest: Forest) -> list[tuple[int, int, str, float]]:
    """``(start, end, kind, score)`` of every candidate, also of those that the forest rejects."""
    if not text or not (found := candidates(text)):
        return []
    x = np.array([describe(text[a:b], text[max(0, a - 48) : a], text[b : b + 16], path or "", kind, forest.words) for a, b, kind in found])
    return [(a, b, kind, float(s)) for (a, b, kind), s in zip(found, forest.predict(x), strict=True)]


def scan_documents(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text", path_col: str = "source") -> DataFrame:
    """``(doc_id, start, end, kind, score, is_secret, value_sha256)``: a row for each candidate, in code points of the whole text.

    Null and empty texts have none. A missing or null path counts as empty. Null ids and repeated rows are scanned like others.
    """
    sent = docs.sparkSession.sparkContext.broadcast(forest or train_forest())

    def make():
        def step(doc, text, path):
            for a, b, kind, score in findings(text, path, sent.value):
                yield doc, a, b, kind, round(score, 6), score >= threshold, hashlib.sha256(text[a:b].encode("utf-8", "surrogatepass")).hexdigest()

        return step

    path = F.col(path_col).cast("string") if path_col in docs.columns else F.lit(None).cast("string")
    return map_rows(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), path.alias("path")), ["doc_id", "text", "path"], make, "doc_id long, start long, end long, kind string, score double, is_secret boolean, value_sha256 string")


def redact(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5, mark: str = "[SECRET]") -> DataFrame:
    """All ``docs``, with each secret replaced by ``mark`` (and ``n_chars`` recounted where that changed the text).

    Null and empty texts stay as they are, and so do null ids, repeated rows and all other columns; a missing or null ``source``
    counts as an empty path. An empty table stays empty. ``docs`` needs a ``text``.
    """
    sent = docs.sparkSession.sparkContext.broadcast(forest or train_forest())
    names = docs.columns
    text, size, path = (names.index(c) if c in names else None for c in ("text", "n_chars", "source"))

    def clean(t: str | None, p: str | None) -> str | None:
        at, out = 0, []
        for a, b, _, score in findings(t, p, sent.value):
            if score >= threshold:
                out += [t[at:a], mark]
                at = b
        return t if not out else "".join(out) + t[at:]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                old, columns = part.column(text).to_pylist(), list(part.columns)
                paths = part.column(path).to_pylist() if path is not None else [None] * len(old)
                new = [clean(t, p) for t, p in zip(old, paths, strict=True)]
                columns[text] = pa.array(new, part.schema.field(text).type)
                if size is not None:
                    columns[size] = pa.array([k if a == b else len(b) for k, a, b in zip(part.column(size).to_pylist(), old, new, strict=True)], part.schema.field(size).type)
                yield pa.RecordBatch.from_arrays(columns, schema=part.schema)

    return docs.mapInArrow(run, docs.schema)
