import hashlib

import pytest
from pyspark.sql import functions as F

from pairbundle.operators import cachesim, convert, sampler
from pairbundle.plans.workloads import QUERIES, _accesses, index
from pairbundle.sources.corpora import corpus

#: Hits at 10, 20, ... 100 per cent of the body at the smallest scale.
HITS = {"region_nations": [0, 2, 3, 5, 6, 7, 12, 13, 13, 20], "page_links": [16, 33, 57, 79, 101, 128, 158, 183, 215, 231], "doc_cap5": [61, 132, 201, 263, 343, 450, 526, 605, 673, 756]}


def texts_ordered(spark, small, name):
    return _accesses(spark, small, name)


@pytest.mark.parametrize("name", HITS)
def test_sweep(spark, small, name):
    rows, idx = texts_ordered(spark, small, name)
    rows = rows.cache()
    body = idx.agg(F.sum("byte_len")).first()[0]
    got = {r.share: r.hits for r in cachesim.sweep(cachesim.distances(rows), body).collect()}
    assert [got[s] for s in range(10, 101, 10)] == HITS[name]
    for share in (30, 100):
        assert cachesim.lru(rows, body * share // 100).first().hits == got[share]


def test_by_definition(spark, small):
    rows, _ = texts_ordered(spark, small, "page_links")
    key = ["worker", "step", "object_id", "object_bytes", "distance"]
    assert cachesim.distances_by_join(rows).select(key).orderBy("step").collect() == cachesim.distances(rows).select(key).orderBy("step").collect()


def test_workers_pages_and_warm_epochs(spark):
    a = spark.createDataFrame([(0, k, k % 3, 100) for k in range(6)], "worker int, step long, object_id long, object_bytes long")
    assert [r.distance for r in cachesim.distances(a).orderBy("step").collect()] == [None] * 3 + [200] * 3
    assert cachesim.paged(a).first().object_bytes == 4096
    warm = cachesim.sweep(cachesim.distances(cachesim.repeated(a, 2)), 300, (100,)).first()
    assert (warm.accesses, warm.hits) == (12, 9)


def test_giant_object_evicts_all(spark):
    a = spark.createDataFrame([(0, 0, 1, 10), (0, 1, 9, 500), (0, 2, 1, 10), (0, 3, 9, 500)], "worker int, step long, object_id long, object_bytes long")
    assert cachesim.lru(a, 100).first().hits == 0
    assert cachesim.sweep(cachesim.distances(a), 100, (100,)).first().hits == 0


def test_no_reuse_without_sharing(spark, small):
    idx = index(spark, small, "page_links")
    epoch = sampler.epoch_all(idx)
    rows = cachesim.stream(epoch, idx.withColumnRenamed("byte_len", "object_bytes"), key="sample_id")
    assert cachesim.sweep(cachesim.distances(rows), 10**12, (100,)).first().hits == 0


def test_closed_form(spark, small):
    assert abs(HITS["doc_cap5"][4] / 945 - cachesim.closed_form(0.5, 945, 189)) < 0.06


def test_permutations(spark, small):
    ids = sampler.sample_ids(index(spark, small, "page_links"))
    a, b, c = (sampler.permute(ids, e, 42).orderBy("step").collect() for e in (0, 0, 1))
    assert a == b != c and sorted(r.sample_id for r in c) == list(range(281)) and [r.step for r in c] == list(range(281))


def test_epoch_one(spark, small):
    idx = index(spark, small, "page_links")
    rows = sampler.epoch_one(idx).join(idx, "bundle_id").collect()
    assert len(rows) == 50 and all(r.start_idx <= r.sample_id <= r.end_idx for r in rows)


def test_stream_is_less_random(spark, small):
    ids = sampler.sample_ids(index(spark, small, "doc_cap5"))
    s = sampler.randomness(sampler.stream_shuffle(ids, F.floor(F.col("sample_id") / 1000))).first()
    assert s.n == 945 and s.share < 0.5


def test_concat_keeps_every_text_whole(spark, small):
    bundles = convert.bundles(corpus(spark, small, "doc_cap5")).cache()
    texts = {r.bundle_id: [t.text for t in r.texts] for r in bundles.collect()}
    whole = {k: " ".join(t) for k, t in texts.items()}
    assert {len(t) for t in texts.values()} == {5} and max(map(len, whole.values())) > 256
    assert {r.bundle_id: r.sequence for r in sampler.epoch_concat(bundles).collect()} == whole
    assert {r.bundle_id: r.sequence_md5 for r in QUERIES["epoch_concat"](spark, small).collect()} == {k: hashlib.md5(t.encode()).hexdigest() for k, t in whole.items()}
    cut = {r.bundle_id: r.sequence for r in sampler.epoch_concat(bundles, max_texts=2, max_chars=9).collect()}
    assert cut == {k: " ".join(t[:2])[:9] for k, t in texts.items()}
