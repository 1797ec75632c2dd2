"""The pipeline's stages keep the columns of documents, each takes effect, and awkward rows have defined results."""

import os

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, gone int, _gone int, leak string, component_id long"


def test_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, n = docs.columns, docs.count()
    junk = spark.createDataFrame([(10**6, "12 34", "en", "s", 5), (10**6 + 1, None, None, None, None)], docs.schema)
    kept = corpus_pipeline.language(spark, docs.unionByName(junk), sf_dir)
    assert kept.columns == columns and kept.where("doc_id >= 1000000").count() == 0 and kept.count() >= 0.98 * n
    for stage in (corpus_pipeline.near_duplicates, corpus_pipeline.repeated_passages, corpus_pipeline.benchmark_leaks):
        out = stage(spark, docs, sf_dir)
        assert out.columns == columns and 0 < out.count() < n or stage is corpus_pipeline.repeated_passages
    assert corpus_pipeline.run(spark, sf_dir).agg({"length": "max"}).first()[0] <= 2048


def words(seed: int, n: int) -> str:
    return " ".join(f"w{(seed * 7919 + i * i * 31 + i) % 9973}x" for i in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, clashing names."""
    base, long_text = words(1, 80), words(2, 30_000)
    rows = [(1, base, "en", "a", 1), (2, base, "en", "a", 1), (2, base, "en", "a", 1), (3, base + " end", None, None, None), (4, None, "en", "a", 0), (5, "", "en", "a", 0), (None, base, "en", "a", 1), (6, long_text, "en", "a", 1)]
    rows += [(7, words(3, 60), "en", "a", 1), (7, words(4, 60), "en", "a", 1), (7, words(4, 60), "en", "a", 1), (8, words(4, 60), "en", "b", 1), (9, "12 34", "en", "a", 5)]
    return spark.createDataFrame([(*r, 1, 2, "x", 3) for r in rows], SCHEMA)


def ids(df):
    return sorted(-1 if r.doc_id is None else r.doc_id for r in df.select("doc_id").collect())


def test_stages_on_odd_rows(spark, sf_dir, odd):
    columns = list(corpus_pipeline.COLUMNS)
    spoken = corpus_pipeline.language(spark, odd, sf_dir)
    assert spoken.columns == columns and ids(spoken) == [-1, 1, 2, 2, 3, 6, 7, 7, 7, 8]
    single = corpus_pipeline.near_duplicates(spark, odd, sf_dir)
    assert single.columns == columns and ids(single) == [-1, 1, 4, 5, 6, 7, 7, 9]
    cut = corpus_pipeline.repeated_passages(spark, odd, sf_dir)
    # the null id comes first, so its text stays and later copies go, but for what follows them
    assert cut.columns == columns and ids(cut) == [-1, 3, 4, 5, 6, 7, 7, 7, 9] and cut.where("doc_id = 3").first()["text"] == "end"
    assert corpus_pipeline.benchmark_leaks(spark, odd, sf_dir).count() == odd.count()
    packed = corpus_pipeline.packed(spark, odd, sf_dir)
    assert packed.where("start = 0").count() == odd.count() and packed.where("doc_id = 4").first()["doc_tokens"] == 1


def test_stages_on_an_empty_table(spark, sf_dir, odd):
    nothing = odd.where("false")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, nothing, sf_dir).count() == 0


def test_run_leaves_only_the_last_tables(spark, sf_dir):
    from comovement.llm.shared import shared_folder

    folder = shared_folder(spark).removeprefix("file:")
    before = set(os.listdir(folder))
    corpus_pipeline.run(spark, sf_dir).count()
    assert {name.split("-")[0] for name in set(os.listdir(folder)) - before} == {"stage", "pieces"}
