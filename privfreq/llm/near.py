"""Near-duplicates by min-max hashing, with exact confirmation and connected components.

Each permutation of the shingle hashes gives two values, the smallest and the largest image, so a signature of 2P values
costs P permutations. Bands of values bring documents of like sets into common buckets. Inside a bucket nobody is paired
with everybody: documents are confirmed (on full sets) against a pivot, and what is linked becomes one component. Buckets
that still hold several components after two rounds go to an exact join of their documents by the rare beginnings of
their sets, which finds every link that is left. No bucket is capped, and a group of copies of any size is one component
after a round or two.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: 32 bands of 5 of the 160 values of 80 permutations: at a similarity of 0.8 a pair is missed once in 300,000 times.
PERMUTATIONS, BANDS, ROWS = 80, 32, 5
#: Ids of documents to be read again that a broadcast may hold (8 bytes each); beyond it they are joined.
BROADCAST_IDS = 4_000_000
PIVOT_ROUNDS = 2
#: Links that a single task may join up.
ONE_TASK_EDGES = 1_000_000


def permutation_table(n: int = PERMUTATIONS, seed: int = 11) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers (odd) and offsets of n affine permutations of the 64-bit numbers."""
    x = common.mix(np.arange(1, 2 * n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed))
    return x[:n] | np.uint64(1), x[n:]


def min_max_signature(hashes: np.ndarray, table: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The smallest image under every permutation, then the largest ones."""
    a, b = table
    step = max(1, 500_000 // len(hashes))
    low, high = np.empty(len(a), np.uint64), np.empty(len(a), np.uint64)
    for i in range(0, len(a), step):
        image = hashes[None, :] * a[i : i + step, None] + b[i : i + step, None]
        low[i : i + step], high[i : i + step] = image.min(1), image.max(1)
    return np.concatenate([low, high])


def band_keys(signature: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """One 64-bit key for each band: what its values and its number mix to."""
    values = signature[: bands * rows].reshape(bands, rows)
    key = np.arange(1, bands + 1, dtype=np.uint64)
    for i in range(rows):
        key = common.mix(key * np.uint64(0x9E3779B97F4A7C15) + values[:, i])
    return key.view(np.int64)


def signatures(docs: DataFrame, width: int) -> DataFrame:
    """doc_id, n_shingles, sig (128 bits of the whole set), bands; without words the last two are null."""
    table = permutation_table()

    def run(batches):
        keyed = common.Keyed()
        for batch in batches:
            n, sig, bands = [], [], []
            for text in common.raw(batch.column(1)):
                s = common.shingles(common.words(text), width, keyed)
                n.append(len(s))
                sig.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                bands.append(band_keys(min_max_signature(s, table)) if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(sig, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "sig", "bands"])

    return common.mapped(common.texts(docs), run, "doc_id long, n_shingles long, sig binary, bands array<bigint>")


def full_sets(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """node, its sorted shingle hashes as bytes, for the documents in ids (column node)."""
    spark = docs.sparkSession
    rows = common.texts(docs)
    wanted = None
    if ids.count() <= BROADCAST_IDS:
        wanted = common.broadcast_of(spark, np.sort(ids.toPandas()["node"].to_numpy(np.int64)))
    else:
        rows = rows.join(ids.withColumnRenamed("node", "doc_id"), "doc_id", "left_semi").select("doc_id", "text")

    def run(batches):
        keyed = common.Keyed()
        for batch in batches:
            batch = batch.filter(batch.column(0).is_valid())
            if wanted is not None:
                doc = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                at = np.searchsorted(wanted.value, doc)
                batch = batch.filter(pa.array(wanted.value[np.minimum(at, len(wanted.value) - 1)] == doc if len(wanted.value) else np.zeros(len(doc), bool)))
            for i in range(0, len(batch), 500):
                part = batch.slice(i, 500)
                sets = [common.shingles(common.words(x), width, keyed).tobytes() for x in common.raw(part.column(1))]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.binary())], ["node", "hashes"])

    return common.mapped(rows, run, "node long, hashes binary")


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets share at least `percent` of their union."""

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    first = pairs.join(sets.select(F.col("node").alias("a"), F.col("hashes").alias("x")), "a")
    both = first.join(sets.select(F.col("node").alias("b"), F.col("hashes").alias("y")), "b").select("a", "b", "x", "y")
    size = F.least(F.length("x"), F.length("y")) * 100 >= F.greatest(F.length("x"), F.length("y")) * percent
    return common.mapped(both.where(size), run, "a long, b long").distinct()


def prefix_pairs(open_sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of nodes of different components that could be linked: complete, and few (open_sets: node, comp, hashes).

    Shingles are ordered from rare to frequent. Two sets that share the `o` shingles that a link needs have a first common
    one with at least o-1 shingles behind it in both, so only the beginnings of sets are joined, with that condition on the
    places. A shingle that no other open set has can't be common: it is counted, not joined.
    """

    def spell(batches):
        for batch in batches:
            for node, comp, hashes in zip(*(batch.column(i) for i in range(3)), strict=True):
                t = np.frombuffer(hashes.as_buffer(), np.int64)
                full = [np.full(len(t), v) for v in (node.as_py(), comp.as_py(), len(t))]
                yield pa.RecordBatch.from_arrays([*(pa.array(v, pa.int64()) for v in full), pa.array(t)], ["node", "comp", "n", "token"])

    tokens = common.mapped(open_sets.select("node", "comp", "hashes"), spell, "node long, comp long, n long, token long")
    tokens = common.materialize(tokens, "tokens")
    shared = common.materialize(tokens.groupBy("token").agg(F.count("*").alias("df")).where("df > 1"), "shared")
    lists = tokens.join(shared, "token").groupBy("node", "comp", "n").agg(F.array_sort(F.collect_list(F.struct("df", "token"))).alias("s"))
    reach = F.col("n") - F.ceil(F.col("n") * percent / 100)  # the last place that any link's first common shingle may have
    alone = F.col("n") - F.size("s")
    heads = lists.select("node", "comp", "n", alone.alias("alone"), F.posexplode(F.slice("s", F.lit(1), F.greatest(reach - alone + 1, F.lit(0)).cast("int"))).alias("i", "x"))
    heads = common.materialize(heads.select("node", "comp", "n", (F.col("alone") + F.col("i")).alias("place"), F.col("x.token").alias("token")), "heads")
    common.discard(tokens)
    need = f"ceil({percent} * (l.n + r.n) / {100 + percent})"
    met = heads.alias("l").join(heads.alias("r"), "token").where(f"l.comp < r.comp and 100 * least(l.n, r.n) >= {percent} * greatest(l.n, r.n) and l.place <= l.n - {need} and r.place <= r.n - {need}")
    return met.select(F.least("l.node", "r.node").alias("a"), F.greatest("l.node", "r.node").alias("b"))


def joined_up(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes and the smallest node that each reaches, by minima along links and jumps."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        while not (new == new[new]).all():
            new = new[new]
        if (new == label).all():
            return nodes, nodes[label]
        label = new


def components(edges: DataFrame) -> DataFrame:
    """node, comp (the smallest node reachable) for the nodes of edges (a, b; a written table).

    Up to ONE_TASK_EDGES links are joined up by one task, in 16 bytes a link; more of them by alternating star contractions
    over the cluster. There a node of very many neighbours is never gathered: minima are combined before the shuffle, and
    joins are split.
    """
    if edges.count() <= ONE_TASK_EDGES:

        def whole(batches):
            parts = [[batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1)] for batch in batches]
            if parts:
                node, comp = joined_up(*(np.concatenate(x).astype(np.int64) for x in zip(*parts, strict=True)))
                yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(comp)], ["node", "comp"])

        return common.mapped(edges.select("a", "b").coalesce(1), whole, "node long, comp long")
    return star_components(edges)


def star_components(edges: DataFrame) -> DataFrame:
    """components() by alternating star contractions, for any number of links."""
    now = common.materialize(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    stamp = None
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = common.materialize(both.groupBy("u").agg(F.least("u", F.min("v")).alias("m")), "low")
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = common.materialize(large, "large")
        low2 = common.materialize(large.groupBy("u").agg(F.min("v").alias("m")), "low")
        small = large.join(low2, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(low2.select("u", F.col("m").alias("v"))).distinct()
        after = common.materialize(small, "edges")
        common.discard(now, low, large, low2)
        now = after
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.bit_xor(F.xxhash64("u", "v"))).first()
        if mark == stamp:
            break
        stamp = mark
    roots = now.groupBy("v").agg(F.first("v").alias("comp")).select(F.col("v").alias("node"), "comp")
    return now.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(roots)


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links, itself included), kept (it is that document).

    Linked: shingle sets that share at least `percent` of their union; equal sets always are. Documents without words (null
    and empty texts among them) have 0 shingles and are linked with nothing. A null doc_id is linked with nothing and
    kept. Rows that share an id and a set stay apart as rows, of one component (each such row is kept if the id is). An
    empty table gives no rows.
    """
    spark = docs.sparkSession
    table = common.materialize(signatures(docs, width), "signatures")
    # a smaller set is linked only with its equals: one shingle more or less is too much
    smallest = -(-percent // (100 - percent)) if percent < 100 else 2**31
    linkable = table.where("n_shingles > 0 and doc_id is not null")
    copies = common.materialize(linkable.groupBy("sig").agg(F.min("doc_id").alias("node")), "copies")
    one = linkable.where(F.col("n_shingles") >= smallest).select("sig", F.col("doc_id").alias("node"), F.col("n_shingles").alias("n"), "bands").join(copies, ["sig", "node"])
    buckets = one.select("node", "n", F.explode("bands").alias("key"))
    live = common.materialize(buckets.groupBy("key").agg(F.min("node").alias("low"), F.max("node").alias("high")).where("low <> high").select("key"), "live")
    members = common.materialize(buckets.join(live, "key"), "members")
    sets = common.materialize(full_sets(docs, members.select("node").distinct(), width), "sets")
    labels = None
    tested = links = None
    for step in range(PIVOT_ROUNDS + 1):
        held = members.withColumn("comp", F.col("node")) if labels is None else members.join(labels, "node", "left").select("key", "node", "n", F.coalesce("comp", "node").alias("comp"))
        held = common.materialize(held, "held")
        # first one pivot for all buckets of a group, then each bucket's own: who is left meets many at once
        drawn = F.xxhash64("node", F.lit(step)) if step == 0 else F.xxhash64("node", "key", F.lit(step))
        pivot = F.min(F.struct(drawn.alias("h"), F.col("node").alias("pivot"), F.col("comp").alias("pivot_comp"), F.col("n").alias("pivot_n"))).alias("p")
        open_ = common.materialize(held.groupBy("key").agg(pivot, F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high").select("key", "p.pivot", "p.pivot_comp", "p.pivot_n"), "open")
        if open_.isEmpty():
            break
        if step < PIVOT_ROUNDS:
            met = held.join(open_, "key").where(f"comp <> pivot_comp and 100 * least(n, pivot_n) >= {percent} * greatest(n, pivot_n)").select(F.least("node", "pivot").alias("a"), F.greatest("node", "pivot").alias("b"))
        else:
            left = held.join(open_.select("key"), "key").groupBy("node").agg(F.first("comp").alias("comp"))
            met = prefix_pairs(left.join(sets, "node"), percent)
        pairs = met.distinct()
        pairs = common.materialize(pairs if tested is None else pairs.join(tested, ["a", "b"], "left_anti"), "pairs")
        tested = pairs if tested is None else tested.unionByName(pairs)
        fresh = confirmed(pairs, sets, percent)
        known = labels.select(F.col("node").alias("a"), F.col("comp").alias("b")) if labels is not None else None
        links = common.materialize(fresh if known is None else fresh.unionByName(known), "links")
        labels = common.materialize(components(links), "labels")
        common.discard(held)
    named = table.join(copies, "sig", "left") if labels is None else table.join(copies.join(labels, "node", "left").select("sig", F.coalesce("comp", "node").alias("node")), "sig", "left")
    component = F.coalesce(F.when(F.col("doc_id").isNotNull(), F.col("node")), F.col("doc_id"))
    return named.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def op9_min_max_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(common.read(spark, sf_dir, "documents"), width=2, percent=80)
