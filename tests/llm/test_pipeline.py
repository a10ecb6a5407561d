"""The pipeline's stages against what each promises, and the registered queries."""

import pytest

import corpus_pipeline
from edgeblocks.llm import entry, mixing, simhash
from edgeblocks.storage import materialise


@pytest.fixture(scope="module")
def stages(spark):
    d = "/root/testdata/sf0.01"
    docs, out = spark.read.parquet(f"{d}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES:
        got = materialise(stage(spark, docs, d), name)
        out.append((name, docs, got))
        docs = got
    return d, {n: (a, b) for n, a, b in out}


def test_order_and_columns(stages):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "near_duplicates", "secrets", "mixing", "bpe"]
    for n in names[:-1]:
        assert stages[1][n][0].columns == stages[1][n][1].columns


def test_toxicity_drops_labelled_documents(spark, stages):
    before, after = stages[1]["toxicity"]
    labels = spark.read.parquet(f"{stages[0]}/labels.parquet")
    gone = before.join(after, "doc_id", "left_anti").join(labels, "doc_id")
    toxic = labels.where("toxic = 1").count()
    assert gone.where("toxic = 1").count() > 0.7 * toxic and gone.where("toxic = 0").count() < 0.05 * labels.count()


def test_one_document_of_each_group(stages):
    before, after = stages[1]["near_duplicates"]
    parts = simhash.wide_components(before)
    assert sorted(r.doc_id for r in after.collect()) == sorted(r.component_id for r in parts.select("component_id").distinct().collect())


def test_secrets_go_and_documents_stay(stages):
    before, after = stages[1]["secrets"]
    assert before.count() == after.count() and after.where("text LIKE '%<secret>%'").count() > 0
    same = before.join(after.withColumnRenamed("text", "t2"), "doc_id").where("text = t2").count()
    assert same > 0.8 * before.count()


def test_mixture(stages):
    before, after = stages[1]["mixing"]
    want = {r.doc_id: r.repeats for r in mixing.mix(before).collect() if r.repeats}
    assert {r.doc_id: r["count"] for r in after.groupBy("doc_id").count().collect()} == want


def test_encoding_covers_the_mixture(stages):
    before, after = stages[1]["bpe"]
    assert before.count() == after.count() and after.where("size(ids) <> n_tokens").count() == 0


def test_all_queries_are_registered():
    numbers = sorted(int(n[2:].split("_")[0]) for n in entry.QUERIES)
    assert numbers == list(range(1, 11)) and set(entry.ORACLES) <= set(entry.QUERIES)


def test_clashing_columns(spark):
    """Extra columns named like working columns, nulls everywhere and an empty table pass through every stage."""
    ddl = "doc_id long, text string, lang string, source string, n_chars long, toxic string, row string, key string, spans string, repeats string, hashed string, copy string, `from` string, n string"
    more = ["x"] * 9
    rows = [(1, "some words here token=abcdefgh12", "en", "s", 31, *more), (None, None, None, None, None, *[None] * 9), (2, "", "en", None, 0, *more), (1, "some words here token=abcdefgh12", "en", "s", 31, *more)]
    for data in (rows, []):
        docs = spark.createDataFrame(data, ddl)
        for name, stage in corpus_pipeline.STAGES:
            got = materialise(stage(spark, docs, "/root/testdata/sf0.001"), name)
            if name != "bpe":
                assert got.columns == docs.columns
                docs = got
        assert got.count() == docs.count()
