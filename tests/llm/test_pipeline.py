import corpus_pipeline
from steadysketch.llm import exact_dedup, simhash

SF = "/root/testdata/sf0.001"


def test_stages_keep_columns_and_decide(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, counts = docs.columns, []
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = corpus_pipeline.materialise(stage(spark, docs, SF))
        counts.append(docs.count())
        if name != "byte-level bpe":
            assert docs.columns == columns
        if name == "exact dedup":
            texts = [exact_dedup.normalised(r.text) for r in docs.collect()]
            assert len(texts) == len(set(texts)) == len({exact_dedup.normalised(r.text) for r in before.collect()})
        if name == "simhash near-dedup":
            fps = [simhash.fingerprint(r.text) for r in docs.collect()]
            assert all((a ^ b).bit_count() > 2 for i, a in enumerate(fps) for b in fps[:i])
    assert counts[0] < 200 and counts[1] <= counts[0] and counts[2] <= counts[1] and counts[4] == counts[3] > 0
