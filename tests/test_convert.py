import pytest
from pyspark.sql import functions as F

from pairbundle.model import PAIRS
from pairbundle.operators import addressing, convert
from pairbundle.sources.corpora import corpus


def micro(spark, rows):
    return spark.createDataFrame([(k, m, t, k) for k, (m, t) in enumerate(rows)], PAIRS)


#: name -> pairs, kind, pairs, bundles
MICRO = {
    "single": ([("a", "x")], "one_to_one", 1, 1),
    "fixed": ([("a", "1"), ("b", "2"), ("a", "3"), ("b", "4")], "fixed", 4, 2),
    "hybrid_gap": ([("a", "1"), ("b", "1"), ("b", "2"), ("b", "3"), ("c", None), ("d", "5"), ("d", "6")], "hybrid", 6, 4),
    "same_text_twice": ([("a", "x"), ("a", "x"), ("b", "y")], "hybrid", 3, 2),
    "unicode": ([("é😀", "ü"), ("é😀", "漢字")], "fixed", 2, 1),
    "uni": ([("a", None), ("b", None)], "uni_modal", 2, 2),
}


@pytest.mark.parametrize("name", MICRO)
def test_micro(spark, name):
    rows, kind, n, m = MICRO[name]
    pairs = micro(spark, rows)
    found = convert.bundles(pairs)
    head = convert.build_header(found).first()
    assert (head.kind, head.n_pairs, head.n_bundles) == (kind, n, m)
    assert convert.verify_roundtrip(pairs, found).count() == 0
    got = found.orderBy("bundle_id").collect()
    want = 0
    for r in got:
        size = 8 + len(r.media.encode()) + sum(4 + len(t.text.encode()) for t in r.texts)
        assert (r.byte_offset, r.byte_len) == (want, size)
        want += size
    ids = [i for r in got for i in range(r.start_idx, r.end_idx + 1)]
    assert ids == list(range(n))


def test_empty(spark):
    head = convert.build_header(convert.clusters(convert.fingerprint(micro(spark, []).limit(0)))).first()
    assert (head.n_pairs, head.n_bundles, head.body_bytes) == (0, 0, 0)


def test_null_media_is_rejected(spark):
    assert convert.clusters(convert.fingerprint(micro(spark, [(None, "x"), ("a", "y")]))).count() == 1


def test_collisions_split(spark):
    pairs = micro(spark, [("aa", "1"), ("bb", "2"), ("aa", "3"), ("ccc", "4")])
    one = lambda c: F.lit("same")
    assert convert.clusters(convert.fingerprint(pairs, hash_function=one)).count() == 2
    assert convert.clusters(convert.fingerprint(pairs, hash_function=one, verify=True)).count() == 3


def test_region_nations(spark, small):
    got = convert.summary(corpus(spark, small, "region_nations")).orderBy("bundle_id").collect()
    assert [(r.start_idx, r.end_idx, r.byte_len, r.byte_offset) for r in got] == [(0, 4, 77, 0), (5, 9, 78, 77), (10, 14, 75, 155), (15, 19, 77, 230), (20, 24, 82, 307)]


#: Pairs, bundles and body bytes at the smallest scale.
EXPECTED = {"doc_cap5": (945, 189, 530224), "doc_cap20": (3780, 189, 673087), "doc_caphyb": (2526, 189, 605342), "page_links": (281, 50, 159224), "orders_lineitems": (6000, 1473, 334392), "customer_orders": (1500, 150, 69819), "part_lineitems": (6000, 200, 276119), "supplier_lineitems": (6000, 10, 267498), "conv_turns": (45, 16, 38258), "doc_copies": (200, 189, 470951), "doc_labels": (87, 86, 263681), "bench_hits": (3, 3, 5703), "pages_url": (50, 50, 158616)}


@pytest.mark.parametrize("name", EXPECTED)
def test_sizes(spark, small, name):
    r = convert.classify(convert.clusters(convert.fingerprint(corpus(spark, small, name)))).first()
    assert (r.n_pairs, r.n_bundles, r.body_bytes) == EXPECTED[name]


def test_order_of_input_is_no_matter(spark, small):
    pairs = corpus(spark, small, "doc_copies")
    a = convert.summary(pairs).orderBy("bundle_id").collect()
    b = convert.summary(pairs.repartition(7).orderBy(F.rand(3))).orderBy("bundle_id").collect()
    assert a == b == convert.summary(pairs, mode="window").orderBy("bundle_id").collect()


def test_prefix_sum_ties_and_negative(spark):
    df = spark.createDataFrame([(k, k % 3) for k in range(100)], "k long, v long")
    got = {r.k: r.s for r in addressing.prefix_sum(df, ["k"], {"s": "v"}).collect()}
    assert got == {k: sum(j % 3 for j in range(k)) for k in range(100)}


def test_childless_parents(spark, small):
    from pairbundle.sources.corpora import orders_lineitems

    r = convert.classify(convert.clusters(convert.fingerprint(orders_lineitems(spark, small, keep_childless=True)))).first()
    assert (r.kind, r.n_pairs, r.n_bundles) == ("hybrid", 6000, 1500)


def test_merge(spark, small):
    pairs = corpus(spark, small, "doc_copies")
    parts = [convert.bundles(pairs.where(F.col("pair_ord") % 2 == k)) for k in (0, 1)]
    a = convert.merge(*parts).select("fingerprint", "rep_ord", "n_texts", "text_bytes").orderBy("rep_ord").collect()
    b = convert.clusters(convert.fingerprint(pairs)).select("fingerprint", "rep_ord", "n_texts", "text_bytes").orderBy("rep_ord").collect()
    assert a == b
