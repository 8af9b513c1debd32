"""URL filters: policy rules on hosts and paths, and association rules mined from labelled URLs.

Token combinations that come with the label ``block`` are mined level by level of their size; rules are pruned by confidence and
support, and by shorter rules that say the same. An inverted index puts each rule under that of its tokens which the fewest URLs have.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.runtime import materialise, merged

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Tasks over which the rows of one token are dealt.
SALTS = 16
#: URLs of one set of tokens above which it is hot: at least so many, and at least this share of all.
HOT_ROWS, HOT_SHARE = 64, 1e-4
#: The policy of the query, host and path in one string, and the verdict.
POLICY = (("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block"))


def host_of(url: F.Column) -> F.Column:
    """From after the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; empty without ``://`` or for null."""
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: F.Column) -> F.Column:
    """What follows the host, up to ``?``, ``#`` or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def policy_match(host: F.Column, path: F.Column, policy: tuple[tuple[str, str], ...]) -> tuple[F.Column, F.Column]:
    """The longest fitting rule and its verdict; both null if none fits. A rule is a host, whose subdomains count too, then a path prefix."""
    if len(policy) > 1000:
        raise ValueError("a policy of over 1000 rules belongs in a table")
    if not policy:
        return F.lit(None).cast("string"), F.lit(None).cast("string")
    rule = verdict = F
    for text, says in sorted(policy, key=lambda r: (-len(r[0]), r[0])):
        own, slash, rest = text.partition("/")
        fits = ((host == own) | host.endswith("." + own)) & path.startswith(slash + rest)
        rule, verdict = rule.when(fits, F.lit(text)), verdict.when(fits, F.lit(says))
    return rule.otherwise(F.lit(None)), verdict.otherwise(F.lit(None))


def url_tokens(url: F.Column, host: F.Column, path: F.Column) -> F.Column:
    """Distinct tokens: scheme, each host label by its distance from the end, non-numeric path segments by place, the ending, query keys."""
    labels = F.reverse(F.split(host, r"\."))
    segments = F.filter(F.split(path, "/"), lambda s: (s != "") & ~s.rlike(r"^\d+(\.\w+)?$"))
    keys = F.filter(F.split(F.regexp_extract(url, r"(?s)\?([^#]*)", 1), "&"), lambda s: s != "")
    at = lambda kind, xs: F.transform(xs, lambda x, i: F.concat(F.lit(kind), i.cast("string"), F.lit(":"), x))
    every = F.concat(
        at("host", F.filter(labels, lambda s: s != "")), at("path", segments), F.transform(keys, lambda k: F.concat(F.lit("query:"), F.split(k, "=")[0])),
        F.array(F.concat(F.lit("scheme:"), F.lower(F.regexp_extract(url, r"(?s)^([A-Za-z]+)://", 1))), F.concat(F.lit("ending:"), F.regexp_extract(path, r"\.(\w+)$", 1))),
    )
    return F.array_distinct(F.filter(F.coalesce(every, F.array().cast("array<string>")), lambda t: ~t.endswith(":")))


def _salted(left: DataFrame, right: DataFrame, key: str, how: str = "inner", salts: int = SALTS) -> DataFrame:
    """An equi-join whose left rows of one key are dealt over ``salts`` tasks; ``right``, the small side, is repeated for each."""
    dealt = left.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    return dealt.join(right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))), [key, "_salt"], how).drop("_salt")


def _level(cover: DataFrame, below: DataFrame | None, size: int, least: float) -> DataFrame:
    """``(key, tokens, blocked, all)``: the combinations in ``cover`` that come with a block in ``least`` rows at least, and that fewer
    rows have than any part with one token less. ``below`` has the parts that may grow."""
    found = cover.groupBy("key").agg(F.first("tokens").alias("tokens"), F.sum("blocked").alias("blocked"), F.sum("n").alias("all")).where(F.col("blocked") >= least - 1e-9)
    if below is None:
        return found
    found = materialise(found, "url-found")
    parts = found.select("key", "all", F.explode(F.transform("tokens", lambda t: F.array_remove("tokens", t))).alias("part"))
    free = parts.join(below.select(F.col("tokens").alias("part"), F.col("all").alias("above")), "part").where("all < above").groupBy("key").count().where(F.col("count") == size)
    return found.join(free.select("key"), "key", "left_semi")


def mine_rules(labelled: DataFrame, min_support: float = 0.005, min_confidence: float = 0.8, min_count: int = 5) -> DataFrame:
    """``(rule_id, tokens, support, confidence)`` from ``labelled`` (``tokens array<string>, blocked boolean``).

    A combination must come with a block in a share ``min_support`` of the rows, and in ``min_count`` of them at least. Rules end in
    a block. A rule goes if a rule on some of its tokens is at least as confident. Rows without tokens or label teach nothing; without
    labelled rows there are no rules.

    All combinations of all tokens are judged, level by level of their size, and none is formed of which it is known that it can't stay:
    one with a rare part; one that the same rows have without one of its tokens, as that shorter one is as confident; and one with
    a part that always comes with a block. What is left grows with what the tokens tell apart, not with their number in a row.
    """
    fine = labelled.where("blocked is not null and size(tokens) > 0").select(F.array_sort(F.array_distinct("tokens")).alias("tokens"), F.col("blocked").cast("long").alias("b"))
    rows = materialise(fine.groupBy("tokens").agg(F.count(F.lit(1)).alias("n"), F.sum("b").alias("blocked")).withColumn("row", F.monotonically_increasing_id()), "url-taught")
    total = rows.agg(F.sum("n")).first()[0] or 0
    empty = rows.select(F.lit("").alias("rule_id"), "tokens", F.lit(0.0).alias("support"), F.lit(0.0).alias("confidence")).limit(0)
    if total < min_count:
        return empty
    least, found, below, size = max(min_support * total, min_count), None, None, 1
    # A row of cover is a combination within a row; digests name it (key) and all its tokens but the last (head).
    digest = lambda c: F.unhex(F.md5(F.to_json(c)))
    cover = rows.select("row", "n", "blocked", F.lit(b"").alias("head"), F.explode("tokens").alias("last")).withColumn("tokens", F.array("last")).withColumn("key", digest("tokens"))
    while True:
        level = materialise(_level(cover, below, size, least), "url-level")
        kept = level.where(F.col("blocked") >= min_confidence * F.col("all")).select(F.concat_ws(" + ", "tokens").alias("rule_id"), "tokens", (F.col("blocked") / total).alias("support"), (F.col("blocked") / F.col("all")).alias("confidence"))
        found = kept if found is None else found.unionByName(kept)
        below = level.where(F.col("blocked") < F.col("all"))
        if size == 1:  # what all rows have tells nothing beside another token
            below = below.where(F.col("all") < total)
        if below.isEmpty():
            break
        cover = materialise(_salted(cover, below.select("key"), "key", "left_semi"), "url-cover")
        more = cover.select("row", "head", F.col("last").alias("next"))
        both = cover.join(merged(more), ["row", "head"]).where("last < next")
        cover = both.select("row", "n", "blocked", F.col("key").alias("head"), F.col("next").alias("last"), F.concat("tokens", F.array("next")).alias("tokens")).withColumn("key", digest("tokens"))
        size += 1
    found = materialise(found, "url-rules")
    # A shorter rule shares each of its tokens with the longer: one equi-join on tokens, counted, finds the contained ones.
    part = found.select(F.col("rule_id").alias("short"), F.size("tokens").alias("n"), F.col("confidence").alias("c"), F.explode("tokens").alias("token"))
    inside = found.select("rule_id", "confidence", F.size("tokens").alias("m"), F.explode("tokens").alias("token")).join(part, "token").where("n < m and c >= confidence")
    beaten = inside.groupBy("rule_id", "short", "n").count().where("count = n").select("rule_id").distinct()
    return found.join(beaten, "rule_id", "left_anti").select("rule_id", "tokens", "support", "confidence")


def match_rules(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """``(key, rule_id, confidence)``: of the rules whose tokens a URL (``key, tokens``; distinct keys) all has, the most confident,
    then the last by id."""
    told = materialise(rules.select("rule_id", "confidence", F.col("tokens").alias("needs"), F.explode("tokens").alias("token")), "url-rule-tokens")
    met = urls.select("key", "tokens", F.explode("tokens").alias("token"))
    freq = met.groupBy("token").count().join(told.select("token").distinct(), "token", "left_semi")
    rare = told.join(freq, "token").groupBy("rule_id").agg(F.min_by("token", F.struct("count", "token")).alias("token"))
    index = told.join(rare, ["rule_id", "token"])  # a row for each rule, under the token that the fewest URLs have
    hits = _salted(met, index, "token").where(F.size(F.array_except("needs", "tokens")) == 0)
    return hits.groupBy("key").agg(F.max_by(F.struct("rule_id", "confidence"), F.struct("confidence", "rule_id")).alias("r")).select("key", "r.rule_id", "r.confidence")


def judge_urls(pages: DataFrame, labels: DataFrame | None = None, policy: tuple[tuple[str, str], ...] = POLICY, **mining) -> DataFrame:
    """``(page_id, host, path, rule, verdict, mined_rule, confidence)`` for every row of ``pages``.

    ``labels`` (``page_id, blocked``) teach the miner; without them the URLs that a policy rule fits do, each with its verdict as
    its label. The policy's verdict stands where a rule fits; elsewhere a URL that meets
    a mined rule is blocked and others are allowed. Null urls, and urls without ``://``, have empty host and path and no tokens.
    URLs are matched once for each distinct set of tokens, so a host with a third of the pages costs one row for each of its sets.
    """
    base = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url")).withColumn("host", host_of(F.col("url"))).withColumn("path", path_of(F.col("url")))
    base = base.withColumn("tokens", F.when(F.coalesce(F.instr("url", "://") > 0, F.lit(False)), url_tokens(F.col("url"), F.col("host"), F.col("path"))).otherwise(F.array().cast("array<string>")))
    rule, verdict = policy_match(F.col("host"), F.col("path"), policy)
    if labels is None:
        taught = base.select("tokens", (verdict == "block").alias("blocked"))
    else:
        taught = base.join(labels.select(F.col("page_id").cast("long").alias("page_id"), "blocked").where("page_id is not null").groupBy("page_id").agg(F.max("blocked").alias("blocked")), "page_id").select("tokens", "blocked")
    rules = mine_rules(taught, **mining)
    base = base.withColumn("key", F.unhex(F.md5(F.concat_ws("\n", F.array_sort("tokens")))))
    sets = materialise(base.groupBy("key").agg(F.first("tokens").alias("tokens"), F.count(F.lit(1)).alias("n")), "url-sets")
    hits = materialise(sets.select("key", "n").join(match_rules(sets.select("key", "tokens"), rules), "key", "left"), "url-hits")
    # Sets of many URLs, of which there can be 10,000 at most, are broadcast, with a rule or without; all others meet theirs in a shuffle.
    hot = F.col("n") > F.lit(max(HOT_ROWS, HOT_SHARE * (sets.agg(F.sum("n")).first()[0] or 0)))
    placed = base.join(F.broadcast(hits.where(hot).select("key", F.struct("rule_id", "confidence").alias("hot"))), "key", "left")
    usual = placed.where("hot is null").drop("hot").join(hits.where(~hot & F.col("rule_id").isNotNull()).select("key", "rule_id", "confidence"), "key", "left")
    joined = placed.where("hot is not null").select("*", "hot.rule_id", "hot.confidence").drop("hot").unionByName(usual)
    return joined.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("rule_id").isNotNull(), "block").otherwise("allow")).alias("verdict"), F.col("rule_id").alias("mined_rule"), "confidence")
