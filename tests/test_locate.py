import random

import pytest

from pairbundle.operators import convert, locate, rangetree, reader, sampler
from pairbundle.plans.workloads import QUERIES, index
from pairbundle.sources.corpora import corpus


@pytest.fixture(scope="module")
def hybrid(spark, small):
    return index(spark, small, "page_links").cache()


@pytest.mark.parametrize("rule", ["hash", "search", "theta", "binned", "asof"])
def test_strategies_agree(spark, hybrid, rule):
    n = 281
    asked = spark.createDataFrame([(k,) for k in [*range(-3, n + 3), None, 10**12]], "sample_id long")
    got = sorted(tuple(r) for r in locate.locate(asked, hybrid, {"kind": "hybrid"}, rule).select(*locate.COLUMNS).collect())
    want = sorted((i, r.bundle_id, i - r.start_idx, r.byte_offset, r.byte_len) for r in hybrid.collect() for i in range(r.start_idx, r.end_idx + 1))
    assert got == want


LOOKUPS = {"locate_direct": "pages_url", "locate_ratio": "doc_cap5", "locate_range": "orders_lineitems", "locate_range_search": "orders_lineitems", "locate_range_asof": "orders_lineitems", "locate_range_theta": "page_links", "locate_hash": "orders_lineitems", "locate_uni_modal": "docs_uni", "locate_adaptive_links": "page_links", "tree_walk": "page_links"}


@pytest.mark.parametrize("key", LOOKUPS)
def test_queries_locate_every_id(spark, small, key):
    got = QUERIES[key](spark, small)
    want = [(i, r.bundle_id, i - r.start_idx, r.byte_offset, r.byte_len) for r in index(spark, small, LOOKUPS[key]).collect() for i in range(r.start_idx, r.end_idx + 1)]
    assert sorted(tuple(r) for r in got.collect()) == sorted(w[: len(got.columns)] for w in want) and want


def test_ratio_equals_range(spark, small):
    idx = index(spark, small, "doc_cap5")
    asked = sampler.sample_ids(idx).select("sample_id")
    a = locate.ratio(asked, idx, 5).orderBy("sample_id").collect()
    assert a == locate.range_binned(asked, idx).orderBy("sample_id").collect() and len(a) == 945


def test_direct_equals_ratio_of_one(spark, small):
    idx = index(spark, small, "pages_url")
    asked = sampler.sample_ids(idx).select("sample_id")
    assert locate.direct(asked, idx).orderBy("sample_id").collect() == locate.ratio(asked, idx, 1).orderBy("sample_id").collect()


def test_left_and_strict(spark, hybrid):
    asked = spark.createDataFrame([(0,), (-1,), (None,)], "sample_id long")
    assert locate.locate(asked, hybrid, {"kind": "hybrid"}, how="left").where("bundle_id IS NULL").count() == 2
    with pytest.raises(Exception, match="no sample"):
        locate.locate(asked, hybrid, {"kind": "hybrid"}, strict=True).collect()


def test_beyond_the_bound_of_the_broadcast(spark, hybrid):
    asked = sampler.sample_ids(hybrid).select("sample_id")
    assert locate.range_search(asked, hybrid, most=3).count() == 281


def test_tree(spark, hybrid):
    tree = rangetree.build(hybrid).cache()
    m = hybrid.count()
    depths = {r.depth: r.nodes for r in rangetree.depth_stats(tree).collect()}
    assert max(depths) == m.bit_length() and sum(depths.values()) == m
    nodes = {r.node_id: r for r in tree.collect()}
    for r in nodes.values():
        left, right = (nodes[c].height if c is not None else 0 for c in (r.left_id, r.right_id))
        assert r.height == 1 + max(left, right) and abs(left - right) <= 1
        assert r.left_id is None or nodes[r.left_id].end_idx < r.start_idx
        assert r.right_id is None or nodes[r.right_id].start_idx > r.end_idx
    walk = rangetree.lookup_trace(tree, sampler.sample_ids(hybrid)).collect()
    assert len(walk) == 281 and max(r.comparisons for r in walk) <= m.bit_length()


@pytest.mark.parametrize("order", ["up", "down", "random"])
def test_insertions(order):
    ranges = [(3 * k, 3 * k + 2, 10 * k) for k in range(1000)]
    {"up": lambda: None, "down": ranges.reverse, "random": lambda: random.Random(4).shuffle(ranges)}[order]()
    root = None
    for r in ranges:
        root = rangetree.insert(root, *r)
    assert rangetree.check(root) == 1000 and root.height <= 1.4405 * 10 + 1
    assert rangetree.find(root, 1501) == (5000, 1) and rangetree.find(root, 3000) is None and rangetree.find(root, -1) is None
    with pytest.raises(ValueError):
        rangetree.insert(root, 5, 7, 0)


def test_reader(spark, small):
    pairs = corpus(spark, small, "page_links")
    found = convert.bundles(pairs).cache()
    want = {r.sample_id: (r.media, r.text) for r in convert.as_pairs(found).collect()}
    one = reader.get(found, 77).first()
    assert (one.media, one.text) == want[77]
    asked = sampler.permute(sampler.sample_ids(found)).where("sample_id % 5 = 0")
    got = reader.get_many(asked, found, {"kind": "hybrid"}, ordered=True)
    rows = got.collect()
    assert [r.step for r in rows] == sorted(r.step for r in rows) and all((r.media, r.text) == want[r.sample_id] for r in rows) and len(rows) == 57
    assert [len(b) for b in reader.iter_batches(got, 20)] == [20, 20, 17]
