"""The five stages on a small table, each against the plain version of its decision."""

import corpus_pipeline
from test_texts import near_rows, plain_components, plain_quality

from pathframe.llm import private


def test_stages(spark, tmp_path):
    some = near_rows() + ["clean words number %d of a text that nobody else has written down so far today at all" % i + " mail a.b@c.de" for i in range(3)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in enumerate(some)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    item = some[-1].split("mail")[0]
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([(0, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    d, now, seen = str(tmp_path), docs, {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, now, d)
        out.write.parquet(f"{tmp_path}/{name}")
        before, now = now, spark.read.parquet(f"{tmp_path}/{name}")
        seen[name] = {r["doc_id"]: r for r in now.collect()}
        if name != "bpe_tokens":
            assert now.columns == before.columns
    good = {i for i, t in enumerate(some) if (n := plain_quality(t))[0] >= 10 and 100 * n[4] <= 20 * n[0]}
    assert set(seen["quality_rules"]) == good
    kept = {i for i, (_, _, keep) in plain_components([(i, some[i]) for i in good]).items() if keep}
    assert set(seen["near_dedup"]) == kept
    # the last three texts share windows of the item
    assert set(seen["decontamination"]) == kept - {len(some) - k for k in (1, 2, 3)}
    assert all("@" not in r["text"] and r["n_chars"] == len(r["text"]) for r in seen["personal_data"].values())
    assert set(seen["bpe_tokens"]) == set(seen["decontamination"]) and private.KINDS[0] == "email"
    assert corpus_pipeline.run(spark, d).count() == len(seen["bpe_tokens"])
