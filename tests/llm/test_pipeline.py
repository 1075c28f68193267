import corpus_pipeline as cp


def test_stages_on_a_small_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    ids = {r.doc_id for r in docs.select("doc_id").collect()}
    assert [n for n, _ in cp.STAGES] == ["toxicity", "exact_dedup", "simhash_near_dedup", "mixing", "bpe"]
    from phasewarp.llm.common import shared_folder, stored

    folder = shared_folder(spark)
    sizes = []
    for name, stage in cp.STAGES:
        docs = stored(stage(spark, docs, sf), folder, name)
        assert {r.doc_id for r in docs.select("doc_id").collect()} <= ids
        if name != "bpe":
            assert docs.columns == columns
        sizes.append(docs.count())
    assert sizes[0] >= sizes[1] >= sizes[2] > 0 and sizes[3] == sizes[4]
    assert docs.filter("NOT round_trip").count() == 0
