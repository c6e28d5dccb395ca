"""What clients send: one-hot, split-path, Hadamard and local-hash reports, from hashed (reproducible) coins.

Client tables have rid, item, key; with a boolean column `heavy` for the split path. Row indexes count from 0.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import bucket, coin, coin_of, coin_word, uniform_int
from ..params import Params, threshold


def assign_phase(clients: DataFrame, p: Params) -> DataFrame:
    """Adds phase: 1 for a share r of the clients, by their own hash, so that re-reads and retries agree."""
    return clients.withColumn("phase", F.when(coin(F.col("rid"), p, "phase") < threshold(p.r), 1).otherwise(2).cast("tinyint"))


def encode(position: int | None, m: int) -> list[int]:
    """The vector before flipping: -1 everywhere but for +1 at the position; none for the dummy report."""
    return [1 if b == position else -1 for b in range(m)]


def one_hot_rows(clients: DataFrame, p: Params, silent_heavy: bool = False) -> DataFrame:
    """rid, j, pos: the row drawn and the place of +1 (-1: none, the dummy report of a heavy-path client).

    silent_heavy drops heavy-path clients: it leaks who they are and serves as an ablation only.
    """
    heavy = F.col("heavy") if "heavy" in clients.columns else F.lit(False)
    if silent_heavy:
        clients = clients.where(~heavy)
    j = uniform_int(F.col("rid"), p, "row", p.k).cast("int")
    rows = clients.select("rid", "key", heavy.alias("heavy"), j.alias("j"))
    return rows.select("rid", "j", F.when(F.col("heavy"), -1).otherwise(bucket(F.col("key"), F.col("j"), p)).cast("int").alias("pos"))


def one_hot_bits(clients: DataFrame, p: Params, silent_heavy: bool = False) -> DataFrame:
    """rid, j, b, plus (whether the sent bit is +1): the report spelled out, one row a bit. For small m and checks only."""
    rows = one_hot_rows(clients, p, silent_heavy)
    words = rows.select("rid", "j", "pos", F.explode(F.sequence(F.lit(0), F.lit(-(-p.m // 4) - 1))).alias("i"))
    words = words.select("rid", "j", "pos", "i", coin_word(F.col("rid"), p, "bit", F.col("i")).alias("word"))
    bits = words.select("rid", "j", "pos", F.inline(F.array(*[F.struct((F.col("i") * 4 + s).alias("b"), coin_of(F.col("word"), s).alias("u")) for s in range(4)])))
    flipped = F.col("u") < threshold(p.q)
    return bits.where(F.col("b") < p.m).select("rid", "j", "b", ((F.col("b") == F.col("pos")) != flipped).alias("plus"))


def hadamard_reports(clients: DataFrame, p: Params) -> DataFrame:
    """rid, j, l, sign: one sign of the transformed one-hot vector, at a coordinate drawn uniformly, perhaps flipped."""
    rid = F.col("rid")
    drawn = clients.select("rid", "key", uniform_int(rid, p, "row", p.k).cast("int").alias("j"), uniform_int(rid, p, "coordinate", p.m).cast("int").alias("l"))
    parity = F.bit_count(F.col("l").cast("bigint").bitwiseAND(bucket(F.col("key"), F.col("j"), p))) % 2
    flipped = coin(rid, p, "flip") < threshold(p.hadamard_q)
    return drawn.select("rid", "j", "l", F.when(flipped, 2 * parity - 1).otherwise(1 - 2 * parity).cast("int").alias("sign"))


def local_hash_reports(clients: DataFrame, p: Params) -> DataFrame:
    """rid, j, y: the small hash under one of k_pool shared functions, kept or replaced by another value."""
    rid = F.col("rid")
    drawn = clients.select("rid", "key", uniform_int(rid, p, "row", p.k_pool).cast("int").alias("j"))
    y = bucket(F.col("key"), F.col("j"), p, p.k_pool, p.g)
    other = (y + 1 + uniform_int(rid, p, "other", p.g - 1)) % p.g
    return drawn.select("rid", "j", F.when(coin(rid, p, "keep") < threshold(p.keep), y).otherwise(other).cast("int").alias("y"))


def bit_vector_reports(clients: DataFrame, domain: DataFrame, p: Params, kind: str = "symmetric") -> DataFrame:
    """rid, item, plus: a randomised bit for every item of a small domain.

    symmetric: every bit tells the truth with chance e^(eps/2)/(e^(eps/2)+1); asymmetric: the own bit with 1/2, others are
    set with chance 1/(e^eps+1).
    """
    keep, set_ = bit_vector_rates(p, kind)
    pairs = clients.select("rid", F.col("item").alias("own")).crossJoin(F.broadcast(domain.select("item")))
    u = coin_of(F.md5(F.concat_ws("|", "rid", F.lit(str(p.seed)), F.lit(kind), F.col("item").cast("string"))))
    return pairs.select("rid", "item", (u < F.when(F.col("own") == F.col("item"), threshold(keep)).otherwise(threshold(set_))).alias("plus"))


def bit_vector_rates(p: Params, kind: str) -> tuple[float, float]:
    """Chance that the own bit is sent as set, and that another one is."""
    if kind == "symmetric":
        return 1 - p.q, p.q
    if kind == "asymmetric":
        return 0.5, 1 / (2.718281828459045**p.eps + 1)
    raise ValueError(kind)


def own_hash_reports(clients: DataFrame, p: Params) -> DataFrame:
    """rid, a, b, y: local hashing in which every client draws a hash function of its own."""
    rid = F.col("rid")
    a = 1 + F.conv(F.substring(coin_word(rid, p, "a"), 1, 15), 16, 10).cast("bigint") % 2147483646
    b = F.conv(F.substring(coin_word(rid, p, "b"), 1, 15), 16, 10).cast("bigint") % 2147483647
    drawn = clients.select("rid", "key", a.alias("a"), b.alias("b")).withColumn("h", (F.col("a") * F.col("key") + F.col("b")) % 2147483647 % p.g)
    other = (F.col("h") + 1 + uniform_int(rid, p, "other", p.g - 1)) % p.g
    return drawn.select("rid", "a", "b", F.when(coin(rid, p, "keep") < threshold(p.keep), F.col("h")).otherwise(other).alias("y"))


def bloom_reports(clients: DataFrame, p: Params, hashes: int = 2) -> DataFrame:
    """rid, b, plus: a Bloom filter of m bits with `hashes` functions, every bit flipped so that the whole costs eps."""
    flip = threshold(1 / (2.718281828459045 ** (p.eps / (2 * hashes)) + 1))
    places = F.array(*[bucket(F.col("key"), F.lit(j), p, hashes) for j in range(hashes)])
    rows = clients.select("rid", places.alias("places"), F.explode(F.sequence(F.lit(0), F.lit(p.m - 1))).alias("b"))
    u = coin_of(F.md5(F.concat_ws("|", "rid", F.lit(str(p.seed)), F.lit("bloom"), F.col("b").cast("string"))))
    return rows.select("rid", "b", (F.array_contains("places", F.col("b").cast("bigint")) != (u < flip)).alias("plus"))
