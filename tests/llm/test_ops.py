"""The operators against brute force, the libraries they must equal, and held-out accuracy."""

import hashlib
import random
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from spurline.llm import ann, bpe, chat, near_dup, packing, quality_fm, quality_rules, queries, secret_scan
from spurline.runtime import table


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r.doc_id: r.text for r in table(spark, sf, "documents").collect()}


def test_op1_recall_and_scores(spark, sf):
    rows = [(r.vec_id, r.embedding) for r in table(spark, sf, "embeddings").collect()]
    by, want = dict(rows), defaultdict(set)
    for q, _, i, _ in ann.brute_force(rows, {i for i, _ in rows if i % 100 == 0}):
        want[q].add(i)
    got = queries.op1_nearest(spark, sf).collect()
    hit = sum(r.vec_id in want[r.query_id] for r in got)
    assert hit >= 0.9 * sum(map(len, want.values()))
    assert len(got) == sum(map(len, want.values()))
    for r in got:
        assert r.score == pytest.approx(float(np.sqrt(((np.array(by[r.query_id], float) - np.array(by[r.vec_id], float)) ** 2).sum())), abs=1e-12)
        assert r.vec_id != r.query_id
    for q in want:
        own = sorted((r for r in got if r.query_id == q), key=lambda r: r.rank)
        assert [r.rank for r in own] == list(range(1, len(own) + 1)) and [(r.score, r.vec_id) for r in own] == sorted((r.score, r.vec_id) for r in own)


def test_op1_windows_select(spark):
    """On the larger table recall is at least 0.9 and under a tenth of the vectors is verified."""
    big = "/root/testdata/sf0.1"
    rows = [(r.vec_id, r.embedding) for r in table(spark, big, "embeddings").collect()]
    want = {(q, i) for q, _, i, _ in ann.brute_force(rows, {i for i, _ in rows if i % 100 == 0})}
    got = queries.op1_nearest(spark, big).collect()
    verified = {r.query_id: r.verified for r in got}
    assert len(got) == len(want) and len(want & {(r.query_id, r.vec_id) for r in got}) >= 0.9 * len(want)
    assert sum(verified.values()) < 0.1 * len(verified) * len(rows)


def test_op1_small_and_even_vectors(spark):
    """Fewer candidates than k, equal vectors, several blocks and chunks: all that there is, in order."""
    df = spark.createDataFrame([(i, [1.0, float(i // 3), 0.0]) for i in range(9)] + [(100, [1.0, 0.0, 0.0])], "vec_id long, embedding array<float>").repartition(3)
    got = ann.nearest(df, df.where("vec_id = 100"), dim=3, k=20).collect()
    assert [(r.rank, r.vec_id, r.score) for r in sorted(got, key=lambda r: r.rank)] == [(i + 1, i, float(i // 3)) for i in range(9)]
    one = df.where("vec_id = 100")
    assert ann.nearest(one, one, dim=3).collect() == []


def test_op1_odd_rows(spark):
    v = [(100, [1.0, 0.0]), (0, [0.0, 0.0]), (1, None), (2, [1.0, float("nan")]), (3, [1.0, None]), (4, [1.0, 0.0]), (5, [1.0, 0.0]), (5, [1.0, 0.0]), (6, [2.0, 0.0]), (None, [1.0, 0.0]), (7, [1.0]), (200, [float("inf"), 1.0])]
    df = spark.createDataFrame(v, "vec_id long, embedding array<double>").selectExpr("*", "1 as rank", "'x' as score")
    got = sorted(map(tuple, ann.nearest(df, df.where("vec_id % 100 = 0"), dim=2, k=3).select("query_id", "rank", "vec_id", "score").collect()))
    assert got == [(100, 1, 4, 0.0), (100, 2, 5, 0.0), (100, 3, 5, 0.0)]
    assert ann.nearest(df.limit(0), df.limit(0), dim=2).collect() == []


def test_op2_odd_rows(spark):
    from spurline.llm import urls

    rows = [(1, None), (2, "no scheme"), (3, "http://A.EXAMPLE.org/es/x?q#f"), (4, "http://fr.com/fr/"), (5, "http://xorg/"), (6, "http://example.org/en/12"), (7, "http://org"), (8, "a://b://c.org/"), (8, ""), (None, "http://x.com/de/1?a=b&c")]
    df = spark.createDataFrame(rows, "page_id long, url string").selectExpr("*", "'x' as host", "1 as verdict")
    labels = spark.createDataFrame([], "page_id long, blocked boolean")
    got = {(r.page_id, r.host, r.path, r.rule, r.verdict) for r in urls.judge_urls(df, labels).collect()}
    assert got == {(1, "", "", None, "allow"), (2, "", "", None, "allow"), (3, "a.example.org", "/es/x", "example.org/es/", "block"), (4, "fr.com", "/fr/", "com/fr/", "allow"), (5, "xorg", "/", None, "allow"), (6, "example.org", "/en/12", "example.org/en/1", "block"), (7, "org", "", None, "allow"), (8, "b:", "//c.org/", None, "allow"), (8, "", "", None, "allow"), (None, "x.com", "/de/1", "com/de/", "block")}
    assert urls.judge_urls(df.limit(0), labels).collect() == []


def test_op2_mined_rules_fire(spark):
    from spurline.llm import urls

    rows = [(i, f"http://{'casino' if i % 3 == 0 else 'news'}.example.net/{'x' if i % 2 else 'y'}/{i}") for i in range(240)]
    df = spark.createDataFrame(rows, "page_id long, url string")
    labels = spark.createDataFrame([(i, i % 3 == 0) for i in range(200)], "page_id long, blocked boolean")
    got = urls.judge_urls(df, labels).collect()
    assert all((r.verdict == "block") == (r.page_id % 3 == 0) for r in got) and len(got) == 240
    assert {r.mined_rule for r in got} == {None, "host2:casino"}


def test_op2_rules_of_many_tokens(spark):
    """Only four tokens together reach the confidence: every three of them are met by more rows that are fine."""
    from itertools import product

    from spurline.llm import urls

    parts = (("com", "net"), ("shop", "blog"), ("www", "cdn"), ("de", "fr"))
    rows, taught = [], []
    for choice in product((0, 1), repeat=4):
        for _ in range(40):
            top, name, sub, lang = (part[c] for part, c in zip(parts, choice, strict=True))
            taught.append((len(rows), sum(choice) == 0))
            rows.append((len(rows), f"http://{sub}.{name}.{top}/{lang}/{len(rows)}"))
    df = spark.createDataFrame(rows, "page_id long, url string")
    got = urls.judge_urls(df, spark.createDataFrame(taught, "page_id long, blocked boolean")).collect()
    assert {r.mined_rule for r in got if r.page_id < 40} == {"host0:com + host1:shop + host2:www + path0:de"}
    assert {r.mined_rule for r in got if r.page_id >= 40} == {None}


def test_op2_rules_of_rows_with_many_tokens(spark):
    """Rules on tokens that are common, in rows of many rare ones, and all that a slow count over all combinations finds."""
    from itertools import combinations

    from spurline.llm import urls

    often = [(sorted({"x", "y"} | {f"q{i}k{j}" for j in range(20)}), True) for i in range(4) for _ in range(5)]
    rows = often + [(["x"], False)] * 40 + [(["y"], False)] * 40
    got = urls.mine_rules(spark.createDataFrame(rows, "tokens array<string>, blocked boolean")).collect()
    assert {tuple(r.tokens): (r.support, r.confidence) for r in got} == {("x", "y"): (0.2, 1.0), **{(f"q{i}k{j}",): (0.05, 1.0) for i in range(4) for j in range(20)}}
    rng = np.random.default_rng(7)
    rows = [([f"t{j}" for j in range(8) if rng.random() < 0.5 + 0.4 * (j < 2)] + ["all"] + ["twin", "t2b"] * int(rng.random() < 0.4), None) for _ in range(300)]
    rows = [(t, bool(rng.random() < (0.95 if {"t3", "t4"} <= set(t) else 0.7 if "t2b" in t else 0.1))) for t, _ in rows]
    seen = {}
    for t, b in rows:
        for k in range(1, len(t) + 1):
            for c in combinations(sorted(t), k):
                n = seen.setdefault(c, [0, 0])
                n[0] += b
                n[1] += 1
    found = {c: b / n for c, (b, n) in seen.items() if b >= 5 and b >= 0.8 * n}
    want = {c: x for c, x in found.items() if not any(found.get(s, 0) >= x for k in range(1, len(c)) for s in combinations(c, k))}
    got = urls.mine_rules(spark.createDataFrame(rows, "tokens array<string>, blocked boolean")).collect()
    assert {tuple(r.tokens): r.confidence for r in got} == want and max(map(len, want)) >= 3 and len(got) == len(want)


def test_op2_mined_rules_decide_on_the_tables(spark, sf):
    """Rules mined from the pages that the policy judges block others, on the given tables."""
    got = queries.op2_urls(spark, sf).where("rule is null").collect()
    assert {r.verdict for r in got if r.mined_rule} == {"block"} and {r.verdict for r in got if not r.mined_rule} == {"allow"}
    assert sum(r.mined_rule is not None for r in got) >= 10


def test_op2_long_rows_and_hot_tokens(spark):
    """Rows of more tokens than are learnt from, a token that all rows have, null labels, and one set a third of all rows."""
    from spurline.llm import urls

    rows = [(i, "http://hot.example.net/bad/x" if i % 3 == 0 else f"http://n{i}.example.net/ok/?" + "&".join(f"k{j}=1" for j in range(40))) for i in range(300)]
    df = spark.createDataFrame(rows, "page_id long, url string").selectExpr("*", "1 as _salt", "'t' as tokens", "'r' as rule_id")
    labels = spark.createDataFrame([(i, None if i % 50 == 1 else i % 3 == 0) for i in range(300)], "page_id long, blocked boolean")
    got = urls.judge_urls(df, labels, policy=()).collect()
    assert len(got) == 300 and all((r.verdict == "block") == (r.page_id % 3 == 0) for r in got)


def test_op3_odd_rows(spark):
    rows = [(1, 0, "user", None), (1, 1, None, "<|turn|>\\<s>[/INST]"), (1, 1, "assistant", "a<|end|>\n"), (1, 1, "assistant", "a<|end|>\n"), (None, None, "assistant", ""), (2, 5, "assi\nstant\\", "é")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "1 as offset", "'f' as formatted")
    got = {r.conv_id: r for r in chat.read_back(chat.format_conversations(df)).collect()}
    turns = "user\n\n" + "\n<|turn|>\\<s>[/INST]\n" + "assistant\na<|end|>\n\n" * 2
    assert got[1].turns_sha256 == hashlib.sha256(turns.encode()).hexdigest()
    assert (got[1].n_turns, got[1].loss_chars) == (4, 18) and got[None].loss_chars == 0
    assert got[2].turns_sha256 == hashlib.sha256("assi\nstant\\\né\n".encode()).hexdigest()
    assert chat.read_back(chat.format_conversations(df.limit(0))).collect() == []


def test_op3_typed_parts(spark):
    parts = [{"type": "text", "text": "see <|image:0|> "}, {"type": "image", "ref": "a.png", "units": 4}, {"type": "audio", "ref": "b.wav", "units": 2}, {"type": "text", "text": "!"}, {"type": "document", "ref": "c.pdf", "units": None}, {"type": "odd", "ref": "d"}]
    text, found, tokens = chat.PartVisitor().visit(parts)
    assert text == "see <\\|image:0|> <|image:0|><|audio:1|>!<|document:2|><|attachment:3|>"
    assert [f["ref"] for f in found] == ["a.png", "b.wav", "c.pdf", "d"] and tokens == 4 * 256 + 50 + 512 + 1
    assert all(text[f["position"] :].startswith(f"<|{f['kind']}:{f['slot']}|>") for f in found)
    df = spark.createDataFrame([(1, 0, "user", [(p["type"], p.get("text"), p.get("ref"), p.get("units")) for p in parts])], f"conv_id long, turn long, role string, parts {chat.PARTS}")
    r = chat.format_conversations(df).first()
    assert r.tokens_expanded == tokens and [a.ref for a in r.attachments] == ["a.png", "b.wav", "c.pdf", "d"]


@given(st.text(alphabet="<>|/s[]INT\\ax\n", max_size=60))
@settings(max_examples=300, deadline=None)
def test_op3_escaping_is_reversible(text):
    assert chat.unescape(chat.escape(text)) == text
    assert chat.unescape_role(chat.escape_role(text)) == text and "\n" not in chat.escape_role(text)
    assert all(x not in chat.escape(text) for x in ("</s>", "<s>", "[INST]", "[/INST]", chat.TURN))


def multi():
    import tiktoken

    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    return bpe.Codec(ranks, P.PATTERN), tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


CODEC, TIK = multi()


def test_op4_equals_library(spark, sf, texts):
    for r in queries.op4_bpe(spark, sf).collect():
        ids, raw = TIK.encode_ordinary(texts[r.doc_id] or ""), (texts[r.doc_id] or "").encode()
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest(), hashlib.sha256(raw).hexdigest())


@given(st.text(max_size=80) | st.text(alphabet="ab \n\t'sre1 .\u00a0é漢😀\u2003\x1c\x85", max_size=60))
@settings(max_examples=500, deadline=None)
def test_op4_any_text(text):
    text = text.encode("utf-8", "ignore").decode()
    assert np.frombuffer(CODEC.encode(text), "<u4").tolist() == TIK.encode_ordinary(text)
    assert CODEC.decode(CODEC.encode(text)) == text.encode()


def test_op4_other_patterns():
    """A pattern that cuts elsewhere than at spaces is followed as the library follows it."""
    import tiktoken

    for pattern in (r"\p{Lu}?\p{Ll}+| ?\p{N}|\s+|.", r"[^ ]+ ?| +"):
        own, lib = bpe.Codec(CODEC.ranks, pattern), tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=CODEC.ranks, special_tokens={})
        for text in ("the CamelCase of someWords in a row. And x12 y", "a b  c ", " Ab, cD"):
            assert np.frombuffer(own.encode(text), "<u4").tolist() == lib.encode_ordinary(text)
    with pytest.raises(ValueError, match="pattern"):
        packing.WholeTextEncoder(open(P.path("byte_bpe_50k.json"), encoding="utf-8").read(), r"\s+|\S+", 1)


def test_memory_of_pieces_is_bounded():
    from spurline.llm.pretokens import Memo

    memo = Memo(10_000)
    for i in range(1000):
        assert memo.keep(f"k{i}", b"x" * 100) == b"x" * 100
    assert 20 < len(memo) < 40 and memo.keep("a" * 50_000, 1) == 1 and "a" * 50_000 not in memo


def test_op4_long_pre_tokens():
    rng = random.Random(1)
    for word in ("a" * 50_000, "".join(rng.choices("abcdehinorstu", k=60_000)), "ab" * 20_000, "é漢" * 4000):
        assert np.frombuffer(CODEC.encode(word), "<u4").tolist() == TIK.encode_ordinary(word)


def test_op5_redacts(spark):
    key = "f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda"
    rows = [(1, f'the token = "{key}" here', "s", 3), (2, "commit sha " + key[::-1], None, None), (3, None, None, None), (4, "", "x", 0), (5, "AKIA" + "Q7" * 8, "x", 20), (None, "plain words only", "x", 16), (6, "uuid 123e4567-e89b-12d3-a456-426614174000 ok", "x", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, n_chars long").selectExpr("*", "1 as start", "2 as kind")
    got = {r.doc_id: r for r in secret_scan.redact(df).collect()}
    assert got[1].text == 'the token = "[SECRET]" here' and got[1].n_chars == len(got[1].text)
    assert got[2].text == rows[1][1] and got[3].text is None and got[4].text == "" and got[5].text == "[SECRET]" and got[6].text == rows[6][1]
    assert {(r.doc_id, r.start, r.end) for r in secret_scan.scan_documents(df).where("is_secret").collect()} == {(1, 13, 53), (5, 0, 20)}
    assert secret_scan.scan_documents(df.limit(0)).collect() == []


def test_op5_long_values(spark):
    """A value of any length is one finding up to its end, and no part of it stays in the text."""
    rng, letters = random.Random(3), "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
    value = {n: "".join(rng.choices(letters, k=n)) for n in (512, 513, 900, 7000)}
    df = spark.createDataFrame([(n, f'api_key = "{v}" end') for n, v in value.items()], "doc_id long, text string")
    got = {(r.doc_id, r.start, r.end, r.is_secret, r.value_sha256) for r in secret_scan.scan_documents(df).collect()}
    assert got == {(n, 11, 11 + n, True, hashlib.sha256(v.encode()).hexdigest()) for n, v in value.items()}
    assert {r.text for r in secret_scan.redact(df).collect()} == {'api_key = "[SECRET]" end'}


def slow_counts(text):
    import re

    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    windows = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    many, inside = Counter(windows), set()
    for i, w in enumerate(windows):
        if many[w] > 1:
            inside |= set(range(i, i + 5))
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(inside)


def test_op6_counts(spark, sf, texts):
    for r in queries.op6_rules(spark, sf).collect():
        n, *rest = want = slow_counts(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (n < 10 or 100 * rest[-1] > 20 * n) and not (r.base_failed and r.kept)


def slow_verdict(text):
    """Kept or not, and word characters lost, from the rules as the docstrings state them."""
    import re
    from fractions import Fraction

    n, chars, _, _, repeated = slow_counts(text)
    lost = 0
    for line in (text or "").split("\n"):
        words = re.findall(r"[^\x20\x09-\x0D]+", line)
        size, many = sum(map(len, words)), len(words)
        bars = len(re.findall(r"\||»| > ", line))
        bad = many >= 3 and bars >= 2 and Fraction(bars, many) >= Fraction(1, 3)
        bad |= many >= 3 and sum(bool(re.search(r"[#*$%&|<>]", w)) for w in words) * 2 > many
        bad |= many >= 3 and 2 * len(re.findall("[0-9]", line)) > size
        bad |= many >= 3 and line.isupper() and ("!!" in line or many >= 8)
        bad |= many >= 8 and len(set(words)) * 4 < many
        bad |= many >= 12 and not re.search(r"[.!?…:;,。！？،।\"')\]]", line)
        bad |= 0 < many <= 12 and any(p in line.lower() for group in quality_rules.BOILERPLATE.values() for p in group)
        lost += size if bad else 0
    return n >= 10 and Fraction(repeated, n) <= Fraction(1, 5) and Fraction(lost, max(chars, 1)) <= Fraction(3, 10), lost


def test_op6_verdicts(spark, sf, texts):
    got = {r.doc_id: (r.kept, r.lost_chars) for r in queries.op6_rules(spark, sf).collect()}
    assert got == {i: slow_verdict(t) for i, t in texts.items()}
    assert {k for k, _ in got.values()} == {True, False} and any(x for _, x in got.values())


LINES = ["Home | News | Sport", "a > b > c", "Mehr erfahren", "Lire la suite", "leer más", "MORE OF IT NOW !!", "1 22 333 4 x", "# $ % word", "plain words without any mark " * 3, "go " * 9, "A sentence, with marks and words enough to count.", "", " \t", "ONE TWO THREE FOUR FIVE SIX SEVEN EIGHT"]


@given(st.lists(st.sampled_from(LINES), max_size=12).map("\n".join))
@settings(max_examples=300, deadline=None)
def test_op6_verdict_of_any_lines(text):
    got = quality_rules.judge(text)
    assert (got[6], got[7]) == slow_verdict(text)


@given(st.lists(st.sampled_from(["a", "b", "c\n", "\n", "d e", "|", "É"]), max_size=60).map(" ".join))
@settings(max_examples=200, deadline=None)
def test_op6_any_text(text):
    assert quality_rules.judge(text)[:5] == slow_counts(text)


def test_op6_keeps_clean_text_and_drops_lines(spark):
    good = "One plain sentence of ordinary words stands here, with a full stop.\nAnd another one follows it, just as plain as the first was."
    rows = [(1, good, 1), (2, good + "\nHome | News | Sport | Contact", 2), (3, "a | b | c | d | e | f | g | h | i | j | k | l", 3), (4, None, None), (5, "", 0), (6, "x" * 200_000, 1), (None, good, 1), (None, good, 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_chars long").selectExpr("*", "'z' as kept")
    got = quality_rules.keep_clean(df)
    assert got.columns == df.columns
    assert sorted((r.doc_id or 0, r.text == good, r.n_chars) for r in got.collect()) == [(0, True, 1), (0, True, 1), (1, True, 1), (2, True, len(good))]
    assert quality_rules.judge_documents(df.limit(0)).collect() == []


def test_op7_pieces(spark, sf, texts):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    want = {i: [*library.encode(t or "", add_special_tokens=False).ids, 1] for i, t in texts.items()}
    rows = queries.op7_packing(spark, sf).collect()
    by, windows = defaultdict(list), defaultdict(list)
    for r in rows:
        ids = want[r.doc_id][r.start : r.start + r.length]
        assert r.doc_tokens == len(want[r.doc_id]) and r.length == len(ids)
        assert r.ids_crc32 == zlib.crc32(struct.pack(f"<{len(ids)}I", *ids))
        by[r.doc_id].append((r.start, r.length))
        windows[r.sequence_id].append((r.offset, r.length))
    for i, ids in want.items():
        at = 0
        for start, n in sorted(by[i]):
            assert start == at
            at += n
        assert at == len(ids)
    for k, parts in windows.items():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at == 2048 or k == max(windows)
    assert sorted(windows) == list(range(len(windows)))


def test_op7_odd_rows(spark):
    long = "aé " * 100_000
    rows = [(1, None), (2, ""), (None, "a  b\n\n c \u00a0d"), (3, "x <|endoftext|> y"), (3, "x <|endoftext|> y"), (4, long)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "0 as start", "'q' as ids", "1 as part")
    got = packing.pack_documents(df).collect()
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    want = [i for _, t in rows for i in [*library.encode(t or "", add_special_tokens=False).ids, 1]]
    assert sum(r.length for r in got) == len(want)
    parts = defaultdict(list)
    for r in got:
        parts[r.doc_id].append(np.frombuffer(r.ids, "<u4").tolist())
    assert parts[1] == [[1]] and parts[2] == [[1]] and sum(parts[None], []) == [*library.encode(rows[2][1]).ids, 1]
    assert packing.pack_documents(df.limit(0)).collect() == []


def auc(score, y):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(y))
    rank[order] = np.arange(1, len(y) + 1)
    p = y.sum()
    return (rank[y == 1].sum() - p * (p + 1) / 2) / (p * (len(y) - p))


def test_op8_held_out(spark, sf):
    labels = {r.doc_id: r.quality for r in table(spark, sf, "labels").collect()}
    rows = queries.op8_quality(spark, sf).collect()
    assert len(rows) == 1000 and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == (r.score >= 0.3) and 0 <= r.score <= 1 for r in rows)
    out = [(r.score, labels[r.doc_id]) for r in rows if r.held_out and r.doc_id in labels]
    s, y = np.array([x[0] for x in out]), np.array([x[1] for x in out])
    assert auc(s, y) > 0.95 and np.mean((s >= 0.3) == y) > 0.9


def test_op8_linear_time_identity():
    m = quality_fm.FactorisationMachine.empty()
    m.w = np.random.default_rng(0).normal(size=m.w.shape).astype(np.float32)
    at, x = quality_fm.features("one two two THREE | four\nfive")
    pairs = sum(float(m.v[a] @ m.v[b]) * x[i] * x[i + 1 + j] for i, a in enumerate(at) for j, b in enumerate(at[i + 1 :]))
    assert m.raw([(at, x)])[0] == pytest.approx(m.bias + float(m.w[at] @ x) + pairs, rel=1e-3, abs=1e-4)


def test_op8_odd_rows(spark):
    df = spark.createDataFrame([(1, None, None), (2, "", 0), (None, "some words", 5), (3, "w " * 100_000, 1)], "doc_id long, text string, n_chars long").selectExpr("*", "2 as score", "1 as y")
    none = spark.createDataFrame([(1, None), (None, 1)], "doc_id long, quality int")
    model = quality_fm.train(df, none)
    assert model is None and {r.score for r in quality_fm.score_documents(df, model).collect()} == {0.5}
    model = quality_fm.train(df, spark.createDataFrame([(i, i % 2) for i in range(1, 4)], "doc_id long, quality int"))
    assert len(quality_fm.score_documents(df, model).collect()) == 4 and quality_fm.keep_good(df, model).columns == df.columns
    assert quality_fm.score_documents(df.limit(0), model).collect() == []


def test_op9_odd_rows(spark):
    from spurline.llm.licenses import scan_licenses

    rows = [(1, None), (2, ""), (3, "All rights reserved"), (None, "x\nReleased under the MIT license!\ny"), (4, "Permission to all"), (5, "a " * 50_000), (6, "This work is licensed under the\nGNU General Public License, version 3.\n\nEnd."), (3, "ALL RIGHTS RESERVED!")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as n", "2 as t", "3 as license")
    got = sorted((r.doc_id or 0, r.unit, r.unit_no, r.license, r.dice) for r in scan_licenses(df).collect())
    assert got == [(0, "line", 1, "mit", 1.0), (0, "paragraph", 0, "mit", 0.8), (3, "line", 0, "reserved", 1.0), (3, "line", 0, "reserved", 1.0), (6, "document", 0, "gpl-3.0", round(22 / 23, 6)), (6, "paragraph", 0, "gpl-3.0", 1.0)]
    assert scan_licenses(df.limit(0)).collect() == []


def test_op9_common_licences_and_notices_inside_lines(spark):
    from spurline.llm.licenses import TEMPLATES, scan_licenses

    prose = "some words of plain prose that say nothing about it "
    inside = prose + "Licensed under the Apache License, Version 2.0. " + prose * 30 + TEMPLATES["bsd-3-clause"] + " " + prose + "(c) Nobody. All rights reserved. " + prose
    names = sorted(TEMPLATES)
    rows = [(i, TEMPLATES[k].upper()) for i, k in enumerate(names)] + [(100, inside), (101, prose * 40), (102, prose + "the license of the software, all conditions reserved " + prose)]
    got = {}
    for r in scan_licenses(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        got.setdefault(r.doc_id, set()).add((r.unit, r.license, r.dice))
    assert {"bsd-2-clause", "bsd-3-clause", "isc", "mpl-2.0", "lgpl-2.1-header", "agpl-3.0-header", "mit-full", "gpl-warranty"} <= set(names)
    assert got == {**{i: {("line", k, 1.0)} for i, k in enumerate(names)}, 100: {("passage", k, 1.0) for k in ("apache-2.0", "bsd-3-clause", "reserved")}}


def test_op9_repeated_bigrams(spark):
    """Dice over bags: a bigram counts as often as both have it."""
    from spurline.llm.licenses import scan_licenses

    templates = {"twice": "to be or not to be or not to be free", "once": "all of these words stand here one time"}
    texts = ["to be or not to be or not to be free", "to be or not to be free", "to be or not to be or not to be or not to be free", "all of these words stand here one time all of"]

    def dice(text, template):
        a, b = (Counter(zip(t.split(), t.split()[1:], strict=False)) for t in (text, template))
        return 2 * sum((a & b).values()) / (sum(a.values()) + sum(b.values()))

    got = {r.doc_id: (r.license, r.dice) for r in scan_licenses(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), templates).where("unit = 'line'").collect()}
    want = {i: max(((k, round(dice(t, v), 6)) for k, v in templates.items()), key=lambda x: x[1]) for i, t in enumerate(texts)}
    assert got == {i: x for i, x in want.items() if x[1] >= 0.8} and len(got) == 3


def slow_print(text):
    import re

    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    grams = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) > 2 else [" ".join(words)] if words else []
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(prints, ids):
    f = np.array(prints, np.uint64)
    root = list(range(len(f)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for i in range(len(f)):
        for j in np.flatnonzero(np.bitwise_count(f[i + 1 :] ^ f[i]) <= 3) + i + 1:
            root[find(int(j))] = find(i)
    least = {}
    for i, d in enumerate(ids):
        least[find(i)] = min(least.get(find(i), d), d)
    return [least[find(i)] for i in range(len(f))]


def test_op10_equals_brute_force(spark, sf, texts):
    ids = sorted(texts)
    prints = [slow_print(texts[i]) for i in ids]
    want = {(i, f"{p:016x}", c) for i, p, c in zip(ids, prints, slow_components(prints, ids), strict=True)}
    assert {tuple(r) for r in queries.op10_near_dup(spark, sf).collect()} == want


@pytest.mark.parametrize("bucket", [near_dup.BUCKET, 10, 1])
def test_op10_dense_groups(spark, bucket):
    """Whole buckets, buckets split by one segment more and by two find the same groups as all pairs do."""
    from spurline.operators.components import components

    rng = random.Random(bucket)
    prints = set()
    for _ in range(12):
        base = rng.getrandbits(64)
        for _ in range(25):
            x = base
            for _ in range(rng.randint(0, 5)):
                x ^= 1 << rng.randrange(64)
            prints.add(x)
    for i in range(3):  # all in one bucket: two segments and more are equal
        base = rng.getrandbits(64)
        prints |= {base ^ rng.getrandbits(12 + 13 * i) for _ in range(60)}
    prints = sorted(prints)
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    got = {r.id: r.component for r in components(near_dup.near_links(df, bucket), df.selectExpr("fp as id")).collect()}
    want = dict(zip(signed, slow_components(prints, signed), strict=True))
    assert got == want


def test_op10_odd_rows(spark):
    rows = [(5, None), (4, ""), (7, " \n"), (9, "One two"), (3, "one TWO"), (None, "one two"), (3, "one TWO"), (8, "É a b c"), (2, "é a b c"), (6, "w " * 100_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as fp", "'k' as key")
    got = sorted(((r.doc_id or 0), r.component_id) for r in near_dup.near_duplicates(df).collect())
    assert got[:7] == [(0, 3), (2, 2), (3, 3), (3, 3), (4, 4), (5, 4), (6, 6)] and got[8:] == [(8, 8), (9, 3)]
    assert near_dup.near_duplicates(df.limit(0)).collect() == []
    kept = near_dup.drop_near_duplicates(df)
    assert kept.columns == df.columns and sorted(r.doc_id or 0 for r in kept.collect()) == [2, 3, 4, 6, 8]


def test_op10_keeps_one_of_each_group(spark):
    """Null ids, one id with different texts, repeated rows, clashing names, hot groups: one row of each group, the same every time."""
    rows = [(None, "nobody names this text", 1), (None, "nobody names this text", 2), (7, "first text of seven words is here", 3), (7, "second text that differs in all", 4), (7, "second text that differs in all", 5), (9, "second text that differs in all", 6)] + [(100 + i, "a hot text of many copies", 7) for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, _keep int").selectExpr("*", "1 as row_key", "'x' as place", "2 as root", "map('a', 1) as m")
    want = sorted([(0, 1), (7, 3), (7, 4), (100, 7)])
    for parts in (1, 7):
        got = near_dup.drop_near_duplicates(df.repartition(parts))
        assert got.columns == df.columns and sorted((r.doc_id or 0, r._keep) for r in got.collect()) == want
    assert near_dup.drop_near_duplicates(df.limit(0)).collect() == []
    ids = {r.doc_id: r.component_id for r in near_dup.near_duplicates(df).collect()}
    assert ids[9] == 7 and ids[250] == 100 and ids[None] is None
