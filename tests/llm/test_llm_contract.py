import pytest
from comparing import same

from spurline.llm.oracles import ORACLES
from spurline.llm.queries import QUERIES


@pytest.mark.parametrize("name", ORACLES)
def test_sql(spark, sf, name):
    assert same(QUERIES[name](spark, sf), ORACLES[name], sf)


def test_native_plan(spark, sf):
    plan = QUERIES["op9_licenses"](spark, sf)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


def test_pipeline(spark, sf):
    """Each stage against its operator's own verdicts on its own input."""
    import corpus_pipeline as c

    from spurline.llm import near_dup, quality_fm, quality_rules, secret_scan
    from spurline.runtime import materialise, table

    docs = table(spark, sf, "documents")
    columns, seen = docs.columns, [docs]
    for name, stage in c.STAGES:
        docs = materialise(stage(spark, docs, sf), "test")
        seen.append(docs)
        assert name == c.STAGES[-1][0] or docs.columns == columns
    ids = [{r.doc_id for r in d.select("doc_id").distinct().collect()} for d in seen]
    model = quality_fm.train(seen[0], table(spark, sf, "labels"))
    assert ids[1] == {r.doc_id for r in quality_fm.score_documents(seen[0], model).where("score >= 0.3").collect()}
    judged = {r.doc_id: r for r in quality_rules.judge_documents(seen[1]).collect()}
    assert {r.doc_id: r.text for r in seen[2].collect()} == {i: r.cleaned for i, r in judged.items() if r.kept}
    assert ids[3] == {r.component_id for r in near_dup.near_duplicates(seen[2]).collect()}
    assert ids[4] == ids[3] == ids[5] and not secret_scan.scan_documents(seen[4]).where("is_secret").count()
    good = {r.doc_id for r in table(spark, sf, "labels").where("quality = 1").collect()}
    assert len(good & ids[1]) > 0.97 * len(good)


def _folder(spark, path, docs, labels):
    """A folder of tables: documents with nulls, repeated rows and columns whose names the operators use too."""
    columns = "doc_id long, text string, lang string, source string, n_chars long, score double, row_key string, place int, fp long"
    spark.createDataFrame(docs, columns).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path)


@pytest.mark.parametrize("labels", [[], [(1, 1, 0), (2, 0, 1), (None, 1, 0), (3, None, None), (1, 1, 0)]])
def test_pipeline_odd_rows(spark, tmp_path, labels):
    import corpus_pipeline as c

    good = "This is one plain sentence of many ordinary words, and it ends here.\nAnother sentence follows the first, as plain as that one was."
    more = "Quite another text with its own words, which no other document of this small table has.\nIt too has a second line, to be kept."
    odd = [None] * 8
    rows = [(1, good, *odd[:2], 1, 0.5, "k", 1, 2), (1, good, *odd[:2], 1, 0.5, "k", 1, 2), (2, None, *odd[1:]), (3, "", *odd[1:]), (None, more, "en", None, None, None, None, None, None), (5, "word " * 60_000, *odd[1:]), (None, None, *odd[1:]), (6, good + '\ntoken = "f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda" is in this line.', *odd[1:])]
    sf = _folder(spark, tmp_path, rows, labels)
    docs = table_of(spark, sf)
    for name, stage in c.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert docs.columns == table_of(spark, sf).columns, name
        docs = spark.createDataFrame(docs.collect(), docs.schema)
    kept = {(r.doc_id, r.text) for r in docs.collect()}
    assert len(kept) == docs.count() <= 3 and not any("f3ef4d6b" in t for _, t in kept)
    if not labels:  # without labels every score is one half, so all but the rules' and duplicates' decisions keep
        assert {i for i, _ in kept} == {1, None, 6} and any("[SECRET]" in t for _, t in kept)
    pieces = c.run(spark, sf).collect()
    assert sum(r.length for r in pieces if r.start == 0) > 0


def table_of(spark, sf):
    from spurline.runtime import table

    return table(spark, sf, "documents")


def test_pipeline_empty_tables(spark, tmp_path):
    import corpus_pipeline as c

    assert c.run(spark, _folder(spark, tmp_path, [], [])).collect() == []
