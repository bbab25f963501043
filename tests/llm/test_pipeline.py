"""The pipeline against a brute-force run of the same decisions on a small table."""

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from test_near_copies import _kept  # noqa: E402

from tplforge.llm import decontaminate, mixing, quality_rules, substring_dedup  # noqa: E402

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
        out = stage(spark, docs, SF).cache()
        after = {r["doc_id"]: r["text"] for r in out.select("doc_id", "text").collect()}
        if name == "quality_rules":
            want = {r["doc_id"] for r in quality_rules.contract(docs).filter("kept").collect()}
        elif name == "simhash_near_dedup":
            want = _kept(sorted(before.items()))[0]
        elif name == "substring_dedup":
            brute = {i: (n, gone) for i, n, gone, _ in substring_dedup.brute_force(list(before.items()))}
            want = {i for i, (n, gone) in brute.items() if not n or gone < n}
            assert {i: len((t or "").split()) for i, t in after.items()} == {i: brute[i][0] - brute[i][1] for i in want}
        elif name == "decontamination":
            m = decontaminate.Matcher([(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()])
            want = {i for i, t in before.items() if not m.find(t or "")}
        else:
            want = {r["doc_id"] for r in mixing.contract(docs, spark.read.parquet(f"{SF}/labels.parquet")).filter("n_copies > 0").collect()}
        assert set(after) == want, name
        assert out.columns[: len(columns)] == columns
        docs = out.select(*columns)


def test_run_and_empty(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0


def test_odd_tables(spark):
    """Null ids and texts, repeated rows, a very long text, no n_chars, and columns that have the stages' own names."""
    import random

    rng = random.Random(7)
    say = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(n))
    long = say(30_000)
    rows = [(i, say(60)) for i in range(40)]
    rows += [(40, rows[0][1]), (41, rows[1][1] + " and one more"), (42, None), (43, ""), (44, " \n\t"), (None, say(50)), (None, None), (45, long), (46, long + " tail"), (47, rows[3][1]), (47, rows[3][1]), (48, "!!! " * 80)]
    docs = spark.createDataFrame([(i, t, "x", 1, 2, 3, 0.5, 7, "c") for i, t in rows], "doc_id long, text string, cut_text string, cut_id int, kept int, found int, mix_rate double, ID_ int, bad string")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF).cache()
        assert set(columns) <= set(docs.columns), name
        seen[name] = [(r["doc_id"], r["text"]) for r in docs.collect()]
        if name != "source_mixing":
            assert docs.columns == columns, name
    ids = {n: {i for i, _ in v} for n, v in seen.items()}
    assert not ids["quality_rules"] & {42, 43, 44, 48} and {0, 40, 45, None} <= ids["quality_rules"]
    assert not ids["simhash_near_dedup"] & {40, 41, 46, 47} and {0, 1, 3, 45, None} <= ids["simhash_near_dedup"]
    assert set(range(40)) <= ids["decontamination"] and dict(seen["substring_dedup"])[45] == long
    assert {"mix_rate", "mix_copies"} <= set(docs.columns) and docs.columns.count("mix_rate") == 1


def test_mixing_after_the_other_stages(spark):
    """On what the first four stages leave: toxic tokens fall, documents labelled good keep a copy, nothing runs away."""
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf).cache()
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    rated = mixing.mix(docs, labels).cache()
    total = lambda what: [rated.selectExpr(f"sum({what} * n_words * p_{d})").first()[0] for d in mixing.DOMAINS]
    begun, rates, copies = total("1"), total("rate"), total("n_copies")
    assert rates[2] < 0.5 * begun[2] and copies[2] < 0.5 * begun[2]
    assert 0.9 * begun[0] < rates[0] < 1.1 * begun[0]
    assert rated.selectExpr("max(rate)").first()[0] <= mixing.CEILING
    good = rated.join(labels.filter("quality = 1 AND toxic = 0"), "doc_id")
    assert good.filter("n_copies > 0").count() >= 0.95 * good.count()
