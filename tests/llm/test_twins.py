"""The operators' queries against their SQL twins, and all of them on tables of hard rows and on empty ones."""

from collections import Counter

import duckdb
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from distinct_bounds.llm import catalogue

SF = "/root/testdata/sf0.001"
DOCUMENTS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()))
def test_query_equals_its_twin(spark, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = catalogue.queries()[name](spark, SF)
    names = sorted(df.columns)
    con.execute(f"CREATE TABLE want AS {catalogue.oracle_sql()[name]}")
    assert sorted(c[0] for c in con.execute("DESCRIBE want").fetchall()) == names
    listed = ", ".join('"' + n + '"' for n in names)
    assert Counter(tuple(r) for r in df.select(*names).collect()) == Counter(con.execute(f"SELECT {listed} FROM want").fetchall())


@pytest.fixture(scope="module")
def hard(spark, tmp_path_factory):
    """Nulls in every column, empty and very long texts, ties, repeated rows."""
    path = str(tmp_path_factory.mktemp("hard"))
    good = "the river holds its bank while small boats drift slowly past the mill and the old town"
    rows = [(i, f"{good} {i} " * (1 + i % 4), ["en", "de"][i % 2], f"s{i % 3}", 5) for i in range(60)]
    rows += [(70, None, None, None, None), (71, "", "en", "s0", 0), (72, " \n\t", "en", None, 3), (None, "no id at all", "en", "s1", 2), (73, "w" * 300_000, "en", "s2", 1), (74, "a b " * 60_000, "de", "s2", 1)]
    rows += [rows[5], rows[5], (75, rows[6][1], "en", "s1", 9)]
    spark.createDataFrame(rows, DOCUMENTS).write.parquet(f"{path}/documents.parquet")
    labels = [(i, i % 2, int(i % 5 == 0)) for i in range(60)] + [(None, 1, 1), (1, None, None), (5, 1, 0), (999, 1, 1)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame([(1, "http://a.com/x", "<p>x</p>"), (2, None, None), (None, "http://a.com/x", "")], "page_id long, url string, html string").write.parquet(f"{path}/pages.parquet")
    return path, len(rows)


@pytest.mark.parametrize("name", sorted(set(catalogue.queries()) - {"op8_warc"}))
def test_every_row_of_a_hard_table_gets_one(spark, hard, name):
    path, n = hard
    made = catalogue.queries()[name](spark, path).cache()
    assert made.count() == n and made.filter("doc_id = 73").count() == 1 and made.filter("doc_id is null").count() == 1
    none = made.filter("doc_id = 70").first().asDict()
    want = {"op2_bpe": ("n_tokens", 0), "op3_rules": ("n_words", 0), "op5_ngram_join": ("component_id", 70), "op6_personal": ("spans", ""), "op7_language": ("lang_pred", "und"), "op9_exact": ("keep_id", 70), "op10_mixing": ("taken", 0)}
    if name in want:
        key, value = want[name]
        assert none[key] == value
    else:
        assert 0 <= none["score"] <= 1 and none["predicted"] in (0, 1)
    assert len({tuple(r) for r in made.filter("doc_id = 5").collect()}) == (2 if name == "op9_exact" else 1)  # of repeated rows one is kept


@pytest.mark.parametrize("name", sorted(catalogue.queries()))
def test_empty_tables_give_empty_ones(spark, hard, tmp_path, name):
    for t in ("documents", "labels", "pages"):
        spark.read.parquet(f"{hard[0]}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    made = catalogue.queries()[name](spark, str(tmp_path))
    assert made.count() == 0 and made.columns[0] == ("page_id" if name == "op8_warc" else "doc_id")


def test_pipeline_on_hard_and_empty_tables(spark, hard, tmp_path):
    path, n = hard
    docs = spark.read.parquet(f"{path}/documents.parquet").withColumn("copies", F.lit(1)).withColumn("score", F.lit("x"))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        held, docs = docs, stage(spark, docs, path)
        assert docs.columns == held.columns, name
    assert 0 < corpus_pipeline.STAGES[-1][1](spark, docs, path).count() == docs.count() <= 3 * n
    for t in ("documents", "labels"):
        spark.read.parquet(f"{path}/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
