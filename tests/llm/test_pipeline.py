"""The pipeline's stages by what they must keep, and run() against the stages one by one with tables between."""

import corpus_pipeline as pipeline
from levelgrid.llm import jaccard_join, mixing, quality

DATA = "/root/testdata/sf0.001"


def test_run_is_its_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    columns = docs.columns
    held = {}
    for name, stage in pipeline.STAGES:
        out = stage(spark, docs, DATA)
        out.write.parquet(str(tmp_path / name))
        held[name] = docs = spark.read.parquet(str(tmp_path / name))
        if name != "encoding":
            assert docs.columns == columns
    run = pipeline.run(spark, DATA)
    assert sorted((r["doc_id"], r["text"], tuple(r["ids"])) for r in run.collect()) == sorted((r["doc_id"], r["text"], tuple(r["ids"])) for r in docs.collect())

    ids = lambda frame: [r["doc_id"] for r in frame.select("doc_id").collect()]
    every = spark.read.parquet(f"{DATA}/documents.parquet")
    verdicts = {r["doc_id"]: r["kept"] for r in quality.quality_figures(every).collect()}
    assert sorted(ids(held["quality_rules"])) == sorted(k for k, v in verdicts.items() if v)
    classes = {r["doc_id"]: r["class_id"] for r in jaccard_join.near_duplicates(held["quality_rules"]).collect()}
    assert sorted(ids(held["near_duplicates"])) == sorted(set(classes.values()))
    assert sorted(ids(held["secret_scan"])) == sorted(ids(held["near_duplicates"]))
    mix = mixing.Mix(mixing.slim_sizes(held["secret_scan"]))
    taken = {r["doc_id"]: r["taken"] for r in mix.taken().collect()}
    words = {}
    for r in held["source_mix"].collect():
        words[r["doc_id"]] = words.get(r["doc_id"], 0) + len(r["text"].split())
    assert words == {k: v for k, v in taken.items() if v}


def test_queries_are_registered():
    import __spark_entry__ as entry

    names = entry.queries()
    assert "pipeline" in names
    for n in range(1, 11):
        assert sum(name.startswith(f"op{n}_") for name in names) == 1
