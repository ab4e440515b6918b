"""The stages of the pipeline on a small corpus: each one's decisions take effect, clean documents stay."""

import corpus_pipeline
from progmatch.llm.common import settle

from .test_operators import PASSAGE, sentence


def test_stages(spark, tmp_path):
    good = [sentence(i, 60 + i % 40) for i in range(200)]
    bad = [" ".join(w + "###" for w in sentence(i, 40).split()) for i in range(60)]
    texts = [*good, *bad, PASSAGE, PASSAGE + " end", good[3] + " password = hunter22", None, ""]
    docs = spark.createDataFrame([(i, t, "en", f"s{i % 4}", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, 0 if i >= 200 else 1, 0) for i in range(260)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    d, seen = str(tmp_path), {}
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        now = settle(stage(spark, now, d), "stage")
        seen[name] = now
        if name != corpus_pipeline.STAGES[-1][0]:
            assert now.columns == docs.columns
    ids = lambda name: {r["doc_id"] for r in seen[name].select("doc_id").collect()}
    quality, near, secret, mix, coded = (n for n, _ in corpus_pipeline.STAGES)
    assert set(range(200)) <= ids(quality) and not ids(quality) & set(range(200, 260))
    assert ids(near) & {260, 261} == {260}
    assert seen[near].count() == len(ids(near)) == seen[secret].count()
    assert not seen[secret].where("text like '%hunter22%'").count()
    assert ids(mix) <= ids(secret) and ids(coded) == ids(mix) and not seen[coded].where("not round_trip").count()
    assert corpus_pipeline.run(spark, d).count() == seen[coded].count()
