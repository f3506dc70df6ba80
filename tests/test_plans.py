"""Plans that must hold at scale."""

from pyspark.sql import functions as F

from pairbundle.operators import convert, locate, sampler
from pairbundle.plans import audit
from pairbundle.plans.workloads import index
from pairbundle.sources.corpora import corpus, table


def test_media_stay_out_of_the_detection_shuffle(spark, small):
    text = audit.plan_text(convert.clusters(convert.fingerprint(corpus(spark, small, "pages_url"))))
    final = text[: text.index("Exchange")]
    assert "media#" not in final.replace("media_bytes#", "")


def test_no_nested_loops_in_lookups(spark, small):
    idx = index(spark, small, "orders_lineitems")
    asked = sampler.sample_ids(idx).select("sample_id")
    for f in (locate.range_binned, locate.range_asof, locate.range_search, locate.hashed):
        assert not any("NestedLoop" in k or "Cartesian" in k for k in audit.operators(f(asked, idx)))
    assert any("NestedLoop" in k or "Cartesian" in k for k in audit.operators(locate.range_theta(asked, idx)))


def test_pruning_and_pushdown(spark, small):
    df = table(spark, small, "lineitem").where(F.col("l_quantity") > 49).select("l_orderkey")
    assert audit.read_columns(df) == {"l_orderkey", "l_quantity"} and any("GreaterThan(l_quantity" in p for p in audit.pushed(df))
