"""Keys, hash functions and coins as Spark expressions that other SQL engines reproduce bit for bit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..params import COIN, P31, Params


def string_key(x: Column) -> Column:
    return F.conv(F.substring(F.md5(x), 1, 15), 16, 10).cast("bigint") % P31


def integer_key(x: Column) -> Column:
    return F.pmod(x.cast("bigint"), F.lit(P31))


def _numbers(values: list[int]) -> Column:
    return F.array(*[F.lit(v).cast("bigint") for v in values])


def affine(key: Column, j: Column, table: list[tuple[int, int]]) -> Column:
    """(a_j * key + b_j) mod P31; j counts from 0."""
    a, b = (F.element_at(_numbers([row[i] for row in table]), j.cast("int") + 1) for i in (0, 1))
    return (a * key + b) % P31


def bucket(key: Column, j: Column, p: Params, n: int | None = None, width: int | None = None) -> Column:
    """Place of a key in row j."""
    return affine(key, j, p.hashes(n)) % (width or p.m)


def sign(key: Column, j: Column, p: Params) -> Column:
    """+1 or -1 for the signed sketch."""
    return 1 - 2 * (affine(key, j, p.hashes(family="s")) % 2)


def coin_word(rid: Column, p: Params, tag: str, i: Column | int = 0) -> Column:
    """md5 of record, seed, tag and number: room for four coins."""
    return F.md5(F.concat_ws("|", rid, F.lit(str(p.seed)), F.lit(tag), (F.lit(i) if isinstance(i, int) else i).cast("string")))


def coin_of(word: Column, slot: int = 0) -> Column:
    """A 28-bit number from a coin word; slot 0 to 3."""
    return F.conv(F.substring(word, 1 + 7 * slot, 7), 16, 10).cast("bigint")


def coin(rid: Column, p: Params, tag: str) -> Column:
    return coin_of(coin_word(rid, p, tag))


def uniform_int(rid: Column, p: Params, tag: str, n: int) -> Column:
    """Uniform in 0..n-1."""
    return F.shiftright(coin(rid, p, tag) * n, COIN.bit_length() - 1)
