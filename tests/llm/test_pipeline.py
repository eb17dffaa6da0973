import hashlib
import os
import random

import corpus_pipeline
from distinct_bounds.llm import catalogue
from distinct_bounds.llm.common import materialize, scratch_dir


def test_stages_one_after_the_other(spark, tmp_path):
    rng = random.Random(9)
    docs, labels = [], []
    for i in range(240):
        text = " ".join(f"{rng.choice('bdfgk')}{rng.choice('aeiou')}{rng.randrange(40)}" for _ in range(40))
        if i % 6 == 0:
            text = " ".join(w + "###" for w in text.split())
        docs.append((i, text, "xx", f"s{i % 3}", len(text)))
        labels.append((i, int(i % 6 != 0), 0))
    docs.append((900, docs[1][1].replace(" ", "  "), "xx", "s0", 1))
    docs.append((901, docs[2][1] + " tail", "xx", "s0", 1))
    docs.append((902, None, None, None, None))
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    at, ids = spark.read.parquet(str(tmp_path / "documents.parquet")), {}
    columns = at.columns
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, at, str(tmp_path))
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == columns, name
        out.write.parquet(str(tmp_path / f"s{k}"))
        at = spark.read.parquet(str(tmp_path / f"s{k}"))
        ids[name] = [r["doc_id"] for r in at.collect()]
    good = set(ids["quality_classifier"])
    assert len(good & {i for i in range(240) if i % 6}) >= 195 and len(good & {i for i in range(240) if i % 6 == 0}) <= 4
    assert 900 not in ids["exact_dedup"] and set(ids["exact_dedup"]) == good - {900}
    assert set(ids["ngram_jaccard"]) == good - {900, 901}
    copies = {i: ids["source_mixing"].count(i) for i in set(ids["source_mixing"])}
    assert set(copies) <= set(ids["ngram_jaccard"]) and max(copies.values()) <= 3
    assert sorted(ids["bpe_encoding"]) == sorted(ids["source_mixing"])
    texts = {d[0]: d[1] or "" for d in docs}
    for r in at.collect():
        assert r["decoded_sha256"] == hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest()
    assert corpus_pipeline.ORACLE_SQL is None
    assert sorted(r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path)).collect()) == sorted(ids["bpe_encoding"])


def test_catalogue_has_one_query_for_each_operator():
    import corpus_pipeline
    from distinct_bounds.llm import catalogue

    names = sorted(catalogue.queries(), key=lambda n: int(n[2:].split("_")[0]))
    assert [int(n[2:].split("_")[0]) for n in names] == list(range(1, 11))
    assert set(catalogue.oracle_sql()) <= set(names)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "exact_dedup", "ngram_jaccard", "source_mixing", "bpe_encoding"]


def test_outputs_of_earlier_stages_do_not_pile_up(spark, tmp_path, monkeypatch):
    def stage(spark, docs, sf_dir):
        return materialize(docs, "within").selectExpr("doc_id", "n + 1 AS n")

    spark.createDataFrame([(i, 0) for i in range(20)], "doc_id long, n long").write.parquet(str(tmp_path / "documents.parquet"))
    monkeypatch.setattr(corpus_pipeline, "STAGES", [("first", stage), ("second", stage), ("third", stage), ("last", lambda spark, docs, sf_dir: docs)])
    before = set(os.listdir(scratch_dir(spark).removeprefix("file:")))
    out = corpus_pipeline.run(spark, str(tmp_path))
    left = [name.split("-")[0] for name in set(os.listdir(scratch_dir(spark).removeprefix("file:"))) - before]
    assert left == ["third"] and [tuple(r) for r in out.orderBy("doc_id").collect()] == [(i, 3) for i in range(20)]
