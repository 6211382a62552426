"""The five stages on the smallest tables, against the operators' own answers."""

from dense_tucker.llm import decontam, pii, quality_crf, simhash


def test_stages(spark, small):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{small}/documents.parquet")
    labels = spark.read.parquet(f"{small}/labels.parquet")
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    at, now = {}, docs
    for name, stage in P.STAGES:
        now = stage(spark, now, small).persist()
        at[name] = now
    assert [n for n, _ in P.STAGES] == ["quality", "near_duplicates", "decontamination", "privacy", "packing"]
    assert all(at[n].columns == docs.columns for n in list(at)[:-1])
    ids = {n: {r["doc_id"] for r in df.select("doc_id").collect()} for n, df in at.items()}
    want = {r["doc_id"] for r in quality_crf.apply(docs, labels).where("predicted = 1").collect()}
    assert ids["quality"] == want
    one = {r["component_id"] for r in simhash.cluster(at["quality"]).collect()}
    assert ids["near_duplicates"] == one
    foul = {r["doc_id"] for r in decontam.apply(at["near_duplicates"], bench).where("contaminated").collect()}
    assert ids["decontamination"] == one - foul
    assert ids["privacy"] == ids["decontamination"] == ids["packing"]
    assert all(not pii.base_spans(r["text"]) and r["n_chars"] == len(r["text"]) for r in at["privacy"].collect())
    # which texts share a sequence depends on the partitions; every text's ids do not
    tokens = lambda df: {(r["doc_id"], r["doc_tokens"]) for r in df.collect()}
    assert tokens(P.run(spark, small)) == tokens(at["packing"])
