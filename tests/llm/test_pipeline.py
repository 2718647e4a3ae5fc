import corpus_pipeline
import pytest
from checks import same_rows, views

from finegrain.llm import entries, exact_dedup, near_dedup, quality

FOLDER = "/root/testdata/sf0.01"


def test_stages_in_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "exact_dedup", "near_dedup", "decontamination", "sentencepiece"]
    assert corpus_pipeline.ORACLE_SQL is None


@pytest.fixture(scope="module")
def steps(spark, docs):
    """Every stage's rows, written and read again."""
    from finegrain.sources.staging import staged

    out = [docs]
    for name, stage in corpus_pipeline.STAGES:
        out.append(staged(stage(spark, out[-1], FOLDER), f"test-{name}"))
    return out


def ids(df):
    return {r["doc_id"] for r in df.select("doc_id").collect()}


def test_each_stage_on_its_own_input(spark, docs, steps):
    assert all(s.columns == docs.columns for s in steps[:5])
    labels = spark.read.parquet(f"{FOLDER}/labels.parquet")
    want = {r["doc_id"] for r in quality.quality_scores(steps[0], labels).filter("predicted = 1").collect()}
    assert ids(steps[1]) == want
    assert ids(steps[2]) == {r["doc_id"] for r in exact_dedup.exact_dedup_digest(steps[1]).filter("kept").collect()}
    near = near_dedup.near_duplicates(steps[2]).collect()
    assert ids(steps[3]) == {r["doc_id"] for r in near if r["kept"]} and len({r["class_id"] for r in near}) == steps[3].count()
    assert ids(steps[5]) == ids(steps[4]) <= ids(steps[3])
    assert steps[5].filter("not exact").count() == 0


def test_clean_documents_stay(spark, docs, steps):
    labels = spark.read.parquet(f"{FOLDER}/labels.parquet")
    good = {r["doc_id"] for r in labels.filter("quality = 1").collect()}
    assert len(good - ids(steps[1])) <= 0.01 * len(good)


def test_pipeline_of_odd_rows(spark, odd, no_docs):
    for start in (odd, no_docs):
        docs = start.checkpoint()
        for _, stage in corpus_pipeline.STAGES:
            docs = stage(spark, docs, FOLDER).checkpoint()
        assert docs.count() <= start.count()


def test_dedup_equals_sql(spark):
    assert same_rows(entries.op5_exact_dedup(spark, FOLDER), views(FOLDER), entries.oracle_sql()["op5_exact_dedup"])


def test_all_eleven_are_registered():
    names = list(entries.queries())
    assert [n.split("_")[0] for n in names[:-1]] == [f"op{i}" for i in range(1, 11)] and names[-1] == "pipeline"
