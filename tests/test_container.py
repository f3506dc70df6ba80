import pytest
from pyspark.sql import functions as F

from pairbundle.functions import udfs
from pairbundle.operators import addressing, convert, layouts
from pairbundle.sources import container, legacy
from pairbundle.sources.corpora import corpus


@pytest.fixture(scope="module")
def found(spark, small):
    return convert.bundles(corpus(spark, small, "page_links")).cache()


def rows_of(df):
    return sorted((r.bundle_id, r.start_idx, r.end_idx, bytes(r.media), tuple(r.texts)) for r in df.collect())


@pytest.mark.parametrize("shards", [1, 4, None])
def test_container_roundtrip(spark, found, tmp_path, shards):
    path = f"file://{tmp_path}/box"
    container.write_container(found, path, shards)
    want = sorted((r.bundle_id, r.start_idx, r.end_idx, r.media.encode(), tuple(t.text for t in r.texts)) for r in found.collect())
    assert rows_of(container.read_container(spark, path)) == want
    assert container.read_header(path) == {"kind": "hybrid", "n_pairs": 281, "n_bundles": 50}
    if shards == 1:
        assert len(list((tmp_path / "box").glob("*.bundles"))) == 1


def test_filters_reach_the_index(spark, found, tmp_path):
    path = f"file://{tmp_path}/box"
    container.write_container(found, path, 3)
    one = container.read_container(spark, path).where("start_idx <= 100 AND end_idx >= 100")
    assert one.count() == 1 and one.first().start_idx <= 100
    assert container.read_container(spark, path).where(F.col("bundle_id").isin(3, 4)).count() == 2
    assert container.read_container(spark, path).where("bundle_id > 1000").count() == 0


def test_shards_hold_their_index(spark, found, tmp_path):
    path = f"file://{tmp_path}/box"
    container.write_container(found, path, 3)
    shards = container.read_shards(path)
    assert len(shards) == 3 and sum(s["n_bundles"] for s in shards) == 50 and not list((tmp_path / "box").glob("*.parquet"))
    store, base = container.filesystem(path)
    index = [r for s in shards for r in container.read_index(store, f"{base}/{s['shard']}").to_pylist()]
    assert [r["bundle_id"] for r in index] == list(range(50))
    few = container.BundleReader(path, 1 << 30)
    few.tests.append(("bundle_id", "eq", 3))
    assert len(few.partitions()) == 1
    parts = container.BundleReader(path, 2000)
    assert len(parts.partitions()) > 3
    rows = [r for p in parts.partitions() for b in parts.read(p) for r in b.column("bundle_id").to_pylist()]
    assert sorted(rows) == list(range(50))


def test_one_pair_without_a_job(spark, found, tmp_path):
    path = f"file://{tmp_path}/box"
    container.write_container(found, path, 2)
    want = {r.sample_id: (r.bundle_id, r.media.encode(), r.text) for r in convert.as_pairs(found).join(found.select("start_idx", "bundle_id", "end_idx"), F.expr("sample_id BETWEEN start_idx AND end_idx")).collect()}
    got = {k: container.find_pair(path, k) for k in range(281)}
    assert {k: v[:3] for k, v in got.items()} == want
    assert max(v[3] for v in got.values()) <= 5  # 25 ranges in each shard
    assert container.find_pair(path, 281) is None and container.find_pair(path, -1) is None


def test_empty_container(spark, found, tmp_path):
    path = f"file://{tmp_path}/box"
    container.write_container(found.limit(0), path, 1)
    assert container.read_container(spark, path).count() == 0 and container.read_header(path)["n_bundles"] == 0


def test_bytes_of_a_bundle():
    data = container.encode_bundle(b"media", [b"a", "é".encode(), b""])
    assert len(data) == 8 + 5 + 3 * 4 + 3 and container.decode_bundle(data) == (b"media", [b"a", "é".encode(), b""], len(data))
    fields, at = container.parse_header(container.header_block({"kind": "fixed", "ratio": 5}))
    assert fields["ratio"] == 5 and at > 16
    with pytest.raises(ValueError):
        container.parse_header(b"XXXX" + bytes(20))


def test_validation(spark, small):
    idx = addressing.number(convert.clusters(convert.fingerprint(corpus(spark, small, "orders_lineitems"))))
    assert container.validate(idx).count() == 0
    assert container.validate(idx.withColumn("byte_len", F.when(F.col("bundle_id") == 7, F.col("byte_len") + 1).otherwise(F.col("byte_len")))).count() == 1


@pytest.mark.parametrize("layout", ["loose", "path_table", "pair_record"])
def test_conversion_from_each_layout(spark, small, tmp_path, layout):
    found = convert.bundles(corpus(spark, small, "conv_turns"), order="first_seen").cache()
    pairs = convert.as_pairs(found)
    src = f"file://{tmp_path}/{layout}"
    {"loose": lambda: legacy.write_loose(pairs, src), "path_table": lambda: legacy.write_path_table(found, src), "pair_record": lambda: legacy.write_pair_record(pairs, src)}[layout]()
    dest = f"file://{tmp_path}/box"
    assert legacy.run_conversion(spark, src, layout, dest)["n_bundles"] == 16
    want = sorted((r.bundle_id, r.start_idx, r.end_idx, r.media.encode(), tuple(t.text for t in r.texts)) for r in found.collect())
    assert rows_of(container.read_container(spark, dest)) == want


def test_parquet_layout(spark, found, tmp_path):
    layouts.write_bundles(found, f"file://{tmp_path}/p", 10)
    back = spark.read.parquet(f"file://{tmp_path}/p")
    assert back.count() == 50
    from pairbundle.plans.audit import read_columns

    assert read_columns(back.select("bundle_id", "n_texts")) == {"bundle_id", "n_texts"}


def test_sql_functions(spark, found):
    udfs.register(spark)
    assert spark.sql("SELECT bundle_of(13, 5) AS b, pos_of(13, 5) AS p").first() == (2, 3)
    found.select("bundle_id", F.col("media").cast("binary").alias("media"), F.transform("texts", lambda t: t["text"]).alias("texts")).createOrReplaceTempView("pb_found")
    n = spark.sql("SELECT count(*) FROM (SELECT encode_bundle(media, texts) AS data FROM pb_found) e, LATERAL explode_bundle(e.data) x").first()[0]
    assert n == 281
    assert spark.sql("SELECT sum(length(encode_bundle(media, texts))) FROM pb_found").first()[0] == 159224
