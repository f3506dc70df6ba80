"""The pipeline against brute force, stage by stage, each on its own input."""

import corpus_pipeline as pipeline
from cases import awkward, empty
from pyspark.sql import functions as F

from pairbundle.llm.common import text_key
from pairbundle.llm.sampling import labels_of
from pairbundle.llm.simhash import near_duplicates
from pairbundle.llm.toxicity import score_toxicity


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").cache()
    columns = docs.columns
    toxic = {r.doc_id for r in score_toxicity(docs, labels_of(spark, small)).where("predicted = 1").collect()}
    stages = dict(pipeline.STAGES)
    assert list(stages) == ["toxicity", "exact_dedup", "near_dedup", "mixing", "packing"]
    a = stages["toxicity"](spark, docs, small).cache()
    assert a.columns == columns and {r.doc_id for r in a.collect()} == {r.doc_id for r in docs.collect()} - toxic
    b = stages["exact_dedup"](spark, a, small).cache()
    assert b.columns == columns
    assert {r.doc_id for r in b.collect()} == {r.k for r in a.groupBy("text").agg(F.max("doc_id").alias("k")).collect()}
    c = stages["near_dedup"](spark, b, small).cache()
    assert c.columns == columns and c.count() <= b.count()
    d = stages["mixing"](spark, c, small).cache()
    assert d.columns == columns and {r.doc_id for r in d.collect()} == {r.doc_id for r in c.collect()}
    assert {r.doc_id: r.text for r in d.collect()} == {r.doc_id: r.text for r in c.collect()}
    e = stages["packing"](spark, d, small)
    assert e.select("doc_id").distinct().count() == d.select("doc_id").distinct().count()
    assert e.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 4096").count() == 0


def test_awkward_rows(spark, small):
    for docs in (awkward(spark), empty(spark)):
        for name, stage in pipeline.STAGES:
            out = stage(spark, docs, small)
            if name != "packing":
                assert out.columns == docs.columns
            assert out.count() >= 0
    kept = dict(pipeline.STAGES)["exact_dedup"](spark, awkward(spark), small)
    assert kept.select("doc_id", "text").distinct().count() == kept.count()


def test_near_dedup_keeps_one_of_each_component(spark, small):
    """Against brute force, with repeated rows, near copies that share the least doc_id, and components without ids."""
    groups = [" ".join(f"{stem}{k}" for k in range(400)) for stem in ("alpha", "beta", "gamma", "delta")]
    rows = [(7, groups[0]), (7, groups[0] + " end"), (9, groups[0] + " stop"), (7, groups[1]), (7, groups[1]), (None, groups[2]), (None, groups[2] + " end"), (None, groups[3]), (3, groups[3] + " end")]
    docs = spark.createDataFrame([(k, t, "en", "web", len(t)) for k, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    prints = {r.text_key: int(r.fingerprint, 16) for r in near_duplicates(docs).collect()}
    keyed = [(k is None, k or 0, key, t) for (k, t), key in zip(rows, (r[0] for r in docs.select(text_key()).collect()))]
    want, left = [], list(keyed)
    while left:
        part, grown = [left.pop(0)], True
        while grown:
            near = [x for x in left if any((prints[x[2]] ^ prints[y[2]]).bit_count() <= 4 for y in part)]
            part, left, grown = part + near, [x for x in left if x not in near], bool(near)
        want.append(min(part))
    got = pipeline.without_near_copies(spark, docs, small)
    assert sorted((r.doc_id is None, r.doc_id or 0, r.text) for r in got.collect()) == sorted((n, k, t) for n, k, _, t in want)
    assert len(want) == 4
