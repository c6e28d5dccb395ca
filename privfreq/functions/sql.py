"""The SQL surface: temporary functions, table functions, and views of estimates."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import P31, Params


def register(spark: SparkSession, p: Params = Params()) -> None:
    """pf_key(text), pf_bucket(key, a, b, m), pf_coin(rid, seed, tag, i); table functions probe_rows and encode_bits."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pf_key(x STRING) RETURNS BIGINT RETURN cast(conv(substring(md5(x), 1, 15), 16, 10) AS BIGINT) % {P31}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pf_bucket(x BIGINT, a BIGINT, b BIGINT, m BIGINT) RETURNS BIGINT RETURN ((a * x + b) % {P31}) % m")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION pf_coin(rid STRING, seed STRING, tag STRING, i INT) RETURNS BIGINT "
        "RETURN cast(conv(substring(md5(concat_ws('|', rid, seed, tag, cast(floor(i / 4) AS STRING))), 1 + 7 * (i % 4), 7), 16, 10) AS BIGINT)"
    )
    hashes = p.hashes()

    @F.udtf(returnType="j int, b bigint")
    class probe_rows:
        def eval(self, key: int) -> Iterator[tuple[int, int]]:
            for j, (a, b) in enumerate(hashes):
                yield j, (a * key + b) % 2147483647 % p.m

    @F.udtf(returnType="b int, bit int")
    class encode_bits:
        def eval(self, position: int, m: int) -> Iterator[tuple[int, int]]:
            for b in range(m):
                yield b, 1 if b == position else -1

    spark.udtf.register("probe_rows", probe_rows)
    spark.udtf.register("encode_bits", encode_bits)


def publish(estimates: DataFrame, method: str) -> None:
    """The view freq_<method>, for `SELECT item, f_hat FROM freq_split`."""
    estimates.createOrReplaceTempView(f"freq_{method}")


def sketch_merge():
    """A grouped-aggregate UDF that adds vectors; the builtin sum over (j, b) is preferred wherever cells are rows."""
    import pandas as pd

    @F.pandas_udf("array<bigint>")
    def merge(v: pd.Series) -> list:
        return list(sum(map(__import__("numpy").asarray, v)))

    return merge
