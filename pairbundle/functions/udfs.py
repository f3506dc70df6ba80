"""Functions for SQL sessions. Built-in expressions come first; Python only where bytes are decoded."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def bundle_of(sample_id: Column, ratio: int) -> Column:
    return F.floor(sample_id / F.lit(ratio)).cast("long")


def pos_of(sample_id: Column, ratio: int) -> Column:
    return F.pmod(sample_id, F.lit(ratio))


def _decoded(data: bytes) -> list[str]:
    from pairbundle.sources.container import decode_bundle

    return [t.decode() for t in decode_bundle(data)[1]]


@udtf(returnType="text_pos int, text string")
class ExplodeBundle:
    """The texts of an encoded bundle as rows."""

    def eval(self, data: bytes) -> Iterator[tuple[int, str]]:
        yield from enumerate(_decoded(bytes(data)))


@udtf(returnType="field string, value string")
class ReadHeader:
    """The fields of a header block as rows."""

    def eval(self, data: bytes) -> Iterator[tuple[str, str]]:
        from pairbundle.sources.container import parse_header

        for k, v in sorted(parse_header(bytes(data))[0].items()):
            yield k, str(v)


def encoder():
    """media binary, texts array<string> -> the encoded bundle, in Arrow batches."""
    from pairbundle.sources.container import encode_bundle

    @pandas_udf("binary")
    def encode(media: pd.Series, texts: pd.Series) -> pd.Series:
        return pd.Series([encode_bundle(bytes(m), [x.encode() for x in t]) for m, t in zip(media, texts)])

    return encode


def register(spark: SparkSession) -> None:
    """SQL names: bundle_of(id, ratio), pos_of(id, ratio), explode_bundle(data), read_header(data), encode_bundle(media, texts)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bundle_of(id BIGINT, ratio BIGINT) RETURNS BIGINT RETURN id DIV ratio")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pos_of(id BIGINT, ratio BIGINT) RETURNS BIGINT RETURN pmod(id, ratio)")
    spark.udtf.register("explode_bundle", ExplodeBundle)
    spark.udtf.register("read_header", ReadHeader)
    spark.udf.register("encode_bundle", encoder())
