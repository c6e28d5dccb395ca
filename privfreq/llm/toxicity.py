"""Toxicity by the nearest labelled examples: exact TF-IDF cosine over a block-max inverted index.

Terms are the words of a text without outer signs; every one counts, in the vectors and in their norms. A weight is
(1 + log tf) * idf, times a relevance between FLOOR and 1 that the word's correlation with the label gives (a word that
says nothing about the label keeps FLOOR). Document frequencies are counted over the whole corpus; a word that fewer than a
share RAREST of the documents have is as rare as any, so the words whose frequency must be known are bounded.

The examples are a bounded, hashed choice of labelled rows. The index has all their terms. It cuts the examples, ordered
by their commonest words, into blocks. Rare terms have posting lists, whose sums are made exactly; for frequent terms the
index keeps the largest weight in each block. Both together bound every example of a block: the best blocks of a batch of
texts are scored first, then all blocks that could still change anyone's k nearest. Neighbours vote with weights that fall
with distance; a logistic curve fitted on leave-one-out votes of the examples calibrates the vote. The nearest examples
come along as evidence.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Examples of each label that the index may hold, and how many of all are voted on to calibrate (every n-th of them).
EXAMPLES, CALIBRATION = 8000, 3000
#: Relevance of a word without any, squared correlation with the label of a word with all; share of documents of the rarest words.
FLOOR, FULL, RAREST = 0.05, 1 / 60, 2e-5
#: Chi-squared that chance gives some word.
CHANCE = 8.0
#: Neighbours, examples in a block, terms with block maxima, texts scored at a time.
NEIGHBOURS, BLOCK, FREQUENT, BATCH = 15, 64, 1024, 96
#: Postings added up at a time, and blocks scored at a time.
POSTINGS, SLAB = 500_000, 64
#: Distance at which a neighbour's vote is halved, and the votes that the base rate has.
SOFT, PRIOR_VOTES = 0.1, 0.5
STRIP = b".,;:!?\"'()[]{}<>|&%$#*-+=/\\`~_^@"
_ID_BITS = 21


_ROW_BITS = 12


def flat(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """row, term, count of all terms of up to 4096 texts, by row; a term is a hash of 52 bits."""
    row, word = common.word_hashes(texts, STRIP)
    key, count = np.unique((row.astype(np.uint64) << np.uint64(64 - _ROW_BITS)) | (word >> np.uint64(_ROW_BITS)), return_counts=True)
    return (key >> np.uint64(64 - _ROW_BITS)).astype(np.int64), (key & np.uint64((1 << (64 - _ROW_BITS)) - 1)).astype(np.int64), count


def look_up(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of keys in a sorted table, and which are there."""
    if not len(table):
        return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
    at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return at, table[at] == keys


class Weighting:
    """Term weights: idf of the words whose frequency matters (sorted hashes), relevance of the examples' terms (sorted)."""

    def __init__(self, n: int, words: np.ndarray, counts: np.ndarray, terms: np.ndarray, relevance: np.ndarray):
        least = max(1.0, n * RAREST)
        self.words, self.idf = words, (np.log((1 + n) / (1 + np.maximum(counts, least))) + 1).astype(np.float32)
        self.rare = float(np.log((1 + n) / (1 + least)) + 1)
        self.terms, self.relevance = terms, relevance.astype(np.float32)

    def unit(self, row: np.ndarray, term: np.ndarray, count: np.ndarray, n: int) -> tuple[np.ndarray, ...]:
        """row, number, count and weight of the terms that the index has, in vectors of length 1 over all terms."""
        at, known = look_up(self.words, term)
        idf = np.where(known, self.idf[at] if len(self.idf) else 0, self.rare)
        at, have = look_up(self.terms, term)
        weight = (1 + np.log(count)) * idf * np.where(have, self.relevance[at] if len(self.terms) else 0, FLOOR)
        norm = np.sqrt(np.bincount(row, weight * weight, n))
        return row[have], at[have], count[have], (weight[have] / norm[row[have]]).astype(np.float32)


def leading(row: np.ndarray, column: np.ndarray, count: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sort keys for rows (the last is the first): the frequent terms (column >= 0) that a row has most often and second most.

    They are mostly words that glue sentences, so rows of one language come together.
    """
    some = np.flatnonzero(column >= 0)
    some = some[np.lexsort((-column[some], count[some], row[some]))]
    last = np.searchsorted(row[some], np.arange(n), "right") - 1
    lead = np.full((2, n), -1, np.int64)
    for i in (0, 1):
        at = last - i
        fits = at >= 0
        fits[fits] = row[some[at[fits]]] == np.flatnonzero(fits)
        lead[i, fits] = column[some[at[fits]]]
    return lead[1], lead[0]


class BlockMaxIndex:
    """Sparse unit vectors of n examples (row, term, weight by rows); order: the examples as blocks take them."""

    def __init__(self, n: int, row: np.ndarray, term: np.ndarray, weight: np.ndarray, n_terms: int, order: np.ndarray | None = None, block: int = BLOCK, frequent: int = FREQUENT):
        self.n, self.block, self.blocks = n, block, -(-max(1, n) // block)
        self.width = self.blocks * block
        self.ids = np.full(self.width, -1, np.int64)
        self.ids[:n] = np.arange(n) if order is None else order
        place = np.empty(max(1, n), np.int64)
        place[self.ids[:n]] = np.arange(n)
        at = place[row]
        held = np.bincount(term, minlength=n_terms)
        common_ = np.argsort(-held, kind="stable")[: min(frequent, n_terms)]
        self.column = np.full(n_terms, -1, np.int64)
        self.column[common_] = np.arange(len(common_))
        column = self.column[term]
        often = column >= 0
        self.dense = np.zeros((len(common_), self.width), np.float32)
        self.dense[column[often], at[often]] = weight[often]
        self.most = self.dense.reshape(len(common_), self.blocks, block).max(2)
        rest = np.flatnonzero(~often)
        rest = rest[np.lexsort((at[rest], term[rest]))]
        self.of, self.value = at[rest], weight[rest]
        self.start = np.searchsorted(term[rest], np.arange(n_terms + 1))

    def nearest(self, row: np.ndarray, term: np.ndarray, weight: np.ndarray, n: int, k: int, skip: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """For n unit vectors the k examples of the largest cosine above 0 (-1: none left) and the cosines, to six digits.

        Examples of equal cosines come by their number; skip[i] is left out for vector i.
        """
        column = self.column[term]
        often = column >= 0
        t, r, w = term[~often], row[~often], weight[~often]
        start, size = self.start[t], self.start[t + 1] - self.start[t]
        sums = np.zeros(n * self.width, np.float32)
        ends = np.cumsum(size)
        cuts = np.searchsorted(ends, np.arange(0, int(size.sum()), POSTINGS))  # none without postings
        for i, j in zip(cuts, np.append(cuts[1:], len(size)), strict=False):
            if i == j:
                continue
            many = size[i:j]
            at = np.arange(int(many.sum()))
            at += np.repeat(start[i:j] - (np.cumsum(many) - many), many)
            low = int(r[i]) * self.width
            cell, product = self.of[at], self.value[at]
            cell += np.repeat(r[i:j] * self.width - low, many)
            product *= np.repeat(w[i:j], many)
            part = np.bincount(cell, product)
            sums[low : low + len(part)] += part
        sums = sums.reshape(n, self.width)
        used, local = np.unique(column[often], return_inverse=True)
        q = np.zeros((n, len(used)), np.float32)
        q[row[often], local] = weight[often]
        bound = (sums.reshape(n, self.blocks, self.block).max(2) + q @ self.most[used]) * np.float32(1 + 1e-4) + np.float32(1e-6)
        best = np.full((n, k), -1, np.int64)
        limit = np.full(n, 5e-7, np.float32)

        def take(exact: np.ndarray, who: np.ndarray, first: int) -> None:
            """Bring scores of the examples from place `first` on into the k best keys of the vectors `who`."""
            found, at = np.nonzero(exact > limit[who, None])
            ids = self.ids[first + at]
            keep = np.flatnonzero((ids >= 0) if skip is None else (ids >= 0) & (ids != skip[who[found]]))
            key = (np.rint(exact[found[keep], at[keep]] * 1e6).astype(np.int64) << _ID_BITS) + (1 << _ID_BITS) - 1 - ids[keep]
            of = np.concatenate([np.repeat(np.arange(len(who)), k), found[keep]])
            # one number to sort by: the vector, then the falling key (21 bits of cosine, 21 of the example's number)
            both = np.sort((of << 43) | ((1 << 42) - np.concatenate([best[who].ravel(), key])))
            start = np.searchsorted(both, np.arange(len(who)) << 43)
            best[who] = (1 << 42) - (both[start[:, None] + np.arange(k)] & ((1 << 43) - 1))
            limit[who] = np.maximum((best[who, -1] >> _ID_BITS) / 1e6 - 1.5e-6, 5e-7)

        # every vector's best block, then slabs of blocks that could still change anyone's nearest, by falling bound
        lead = bound.argmax(1)
        for b in np.unique(lead):
            who = np.flatnonzero(lead == b)
            cells = slice(b * self.block, (b + 1) * self.block)
            take(sums[who, cells] + q[who] @ self.dense[used, cells], who, b * self.block)
        everyone = np.arange(n)
        slabs = [np.arange(i, min(i + SLAB, self.blocks)) for i in range(0, self.blocks, SLAB)]
        for slab in sorted(slabs, key=lambda x: -float(bound[:, x].sum())):
            wanted = slab[(bound[:, slab] >= limit[:, None]).any(0)]
            if not len(wanted):
                continue
            first, last = wanted[0] * self.block, (wanted[-1] + 1) * self.block
            exact = q @ self.dense[used, first:last]
            exact += sums[:, first:last]
            # what the first step took is not taken again
            begin = lead * self.block
            for i in np.flatnonzero((begin >= first) & (begin < last)):
                exact[i, begin[i] - first : begin[i] - first + self.block] = -1
            take(exact, everyone, first)
        top = best
        cosine = np.where(top >= 0, top >> _ID_BITS, 0) / 1e6
        ids = np.where(cosine > 0, (1 << _ID_BITS) - 1 - (top & ((1 << _ID_BITS) - 1)), -1)
        return ids, cosine


def vote(ids: np.ndarray, cosines: np.ndarray, labels: np.ndarray, worth: np.ndarray, prior: float) -> np.ndarray:
    """Distance-weighted share of label 1 in each row; worth corrects for how the two labels were chosen."""
    y = np.where(ids >= 0, labels[np.maximum(ids, 0)], 0)
    w = np.where(ids >= 0, worth[y] * cosines / (1 - np.minimum(cosines, 1) + SOFT), 0)
    return ((w * y).sum(1) + PRIOR_VOTES * prior) / (w.sum(1) + PRIOR_VOTES)


def fit_logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Slope and offset of a weighted logistic curve, by Newton steps with a little ridge."""
    a = np.column_stack([x, np.ones(len(x))])
    beta = np.array([1.0, 0.0])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -30, 30)))
        step = np.linalg.solve((a * (w * p * (1 - p))[:, None]).T @ a + 1e-3 * np.eye(2), a.T @ (w * (y - p)) - 1e-3 * (beta - [1.0, 0.0]))
        beta += step
        if abs(step).max() < 1e-8:
            break
    return float(max(beta[0], 1e-3)), float(beta[1])


def logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-6, 1 - 1e-6)
    return np.log(p / (1 - p))


def chosen_examples(labels: DataFrame, label: str, held_out, limit: int) -> tuple[DataFrame, dict[int, float]]:
    """doc_id and label of at most `limit` rows of each label, by the hash of their ids; and how many rows there are of each.

    A doc_id with several label rows has the largest one. Rows without id or label teach nothing.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label")).where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1) & ~held_out)
    known = common.materialize(known.groupBy("doc_id").agg(F.max("label").alias("label")), "labels")
    size = {r["label"]: float(r["count"]) for r in known.groupBy("label").count().collect()}
    parts = [known.where(F.col("label") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit) for y in (0, 1)]
    return parts[0].unionByName(parts[1]), size


def document_frequencies(docs: DataFrame) -> DataFrame:
    """term (64-bit hash), df over all rows of docs; counted in each part before the shuffle."""

    def run(batches):
        parts, waiting = [], 0

        def rows(parts):
            k, n = (np.concatenate(x) for x in zip(*parts, strict=True))
            k, of = np.unique(k, return_inverse=True)
            return k, np.bincount(of, n).astype(np.int64)

        def out(parts):
            return pa.RecordBatch.from_arrays([*map(pa.array, rows(parts))], ["term", "df"])

        for batch in batches:
            texts = common.raw(batch.column(0))
            for i, j in common.pieces(texts):
                k, n = np.unique(np.concatenate([flat(texts[x : min(x + 4096, j)])[1] for x in range(i, j, 4096)]), return_counts=True)
                parts.append((k, n))
                waiting += len(k)
                if waiting > 1_000_000:
                    parts = [rows(parts)]
                    waiting = 0
                    if len(parts[0][0]) > 1_500_000:
                        yield out(parts)
                        parts = []
        if parts:
            yield out(parts)

    return common.mapped(common.texts(docs).select("text"), run, "term long, df long").groupBy("term").agg(F.sum("df").alias("df"))


def relevances(row: np.ndarray, term: np.ndarray, label: np.ndarray, n_terms: int) -> np.ndarray:
    """FLOOR to 1 for each term, by the squared correlation of its being in an example with the example's label."""
    n0, n1 = float((label == 0).sum()), float((label == 1).sum())
    if not n0 or not n1:
        return np.full(n_terms, FLOOR)
    a, b = (np.bincount(term[label[row] == y], minlength=n_terms).astype(float) for y in (0, 1))
    cross = a * n1 - b * n0
    chi2 = (n0 + n1) * cross * cross / (n0 * n1 * np.maximum(a + b, 1) * (n0 + n1 - a - b + 0.5))
    return FLOOR + (1 - FLOOR) * np.minimum(1, np.maximum(0, chi2 - CHANCE) / (n0 + n1) / FULL)


class Judge:
    """Everything that scoring needs; the index itself is built where it is used, out of the examples' sparse vectors.

    vectors: where each example's terms begin (and the end), their numbers, their weights.
    """

    def __init__(self, weighting: Weighting, names: np.ndarray, label: np.ndarray, vectors: tuple, order: np.ndarray, worth: np.ndarray, prior: float, empty: float, k: int):
        self.weighting, self.names, self.label, self.vectors, self.order = weighting, names, label, vectors, order
        self.worth, self.prior, self.empty, self.k = worth, prior, empty, k
        self.held = None

    def __getstate__(self):
        return self.__dict__ | {"held": None}

    def index(self) -> BlockMaxIndex:
        if self.held is None:
            start, term, weight = self.vectors
            row = np.repeat(np.arange(len(self.label)), np.diff(start))
            self.held = BlockMaxIndex(len(self.label), row, term, weight, len(self.weighting.terms), self.order)
        return self.held

    def picked(self) -> np.ndarray:
        """The examples that calibrate: every n-th of them."""
        return np.arange(len(self.label))[:: max(1, len(self.label) // CALIBRATION)]

    def votes(self, some: np.ndarray) -> np.ndarray:
        """What these examples get from all others."""
        start, term, weight = self.vectors
        size = start[some + 1] - start[some]
        at = np.repeat(start[some] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
        near = self.index().nearest(np.repeat(np.arange(len(some)), size), term[at], weight[at], len(some), self.k, some)
        return vote(*near, self.label, self.worth, self.prior)

    def scores(self, texts: list[bytes], slope: float, offset: float) -> tuple[np.ndarray, np.ndarray]:
        """Score and the three nearest examples (their numbers, -1: none) of each text."""
        row, term, count = flat(texts)
        size = np.bincount(row, minlength=len(texts))
        out, near = np.full(len(texts), self.empty), np.full((len(texts), 3), -1, np.int64)
        if not len(self.label):
            return out, near
        index = self.index()
        row, term, count, weight = self.weighting.unit(row, term, count, len(texts))
        # texts of like commonest words go together, so that they ask for the same blocks
        ends = np.searchsorted(row, np.arange(len(texts) + 1))
        order = np.lexsort(leading(row, index.column[term], count, len(texts)))
        for i in range(0, len(order), BATCH):
            some = order[i : i + BATCH]
            length = ends[some + 1] - ends[some]
            at = np.repeat(ends[some] - (np.cumsum(length) - length), length) + np.arange(int(length.sum()))
            ids, cosines = index.nearest(np.repeat(np.arange(len(some)), length), term[at], weight[at], len(some), self.k)
            z = slope * logit(vote(ids, cosines, self.label, self.worth, self.prior)) + offset
            out[some], near[some] = 1 / (1 + np.exp(-z)), ids[:, :3]
        out[size == 0], near[size == 0] = self.empty, -1
        return out, near


def learned(docs: DataFrame, labels: DataFrame, label: str, held_out, examples: int, k: int) -> Judge:
    """The examples, their terms and weights, and the calibration."""
    chosen, size = chosen_examples(labels, label, held_out, examples)
    chosen = common.materialize(chosen, "examples")

    def vectors(batches):
        for batch in batches:
            for i in range(0, len(batch), 500):
                part = batch.slice(i, 500)
                row, term, count = flat(common.raw(part.column(1)))
                ends = pa.array(np.searchsorted(row, np.arange(len(part) + 1)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (term, count.astype(np.int32))]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), *lists], ["doc_id", "label", "terms", "counts"])

    # a doc_id that several texts share teaches with the first of them
    sample = common.texts(docs).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text")).select("doc_id", "text", "label")
    sample = common.mapped(sample, vectors, "doc_id long, label int, terms array<bigint>, counts array<int>").toArrow()
    names, y = sample["doc_id"].to_numpy(), sample["label"].to_numpy().astype(np.int64)
    # the examples hold some ten million words at most; each array of them is dropped as soon as it has served
    sizes = np.concatenate([np.empty(0, np.int64), *[np.diff(c.offsets.to_numpy()) for c in sample["terms"].chunks]]).astype(np.int64)
    hashed = np.concatenate([np.empty(0, np.int64), *[c.flatten().to_numpy() for c in sample["terms"].chunks]])
    tf = np.concatenate([np.empty(0, np.int32), *[c.flatten().to_numpy() for c in sample["counts"].chunks]])
    del sample
    common.free()
    rank = np.argsort(names, kind="stable")
    begin = np.cumsum(sizes) - sizes
    at = np.repeat(begin[rank] - (np.cumsum(sizes[rank]) - sizes[rank]), sizes[rank]) + np.arange(len(hashed))
    names, y, sizes, hashed, tf = names[rank], y[rank], sizes[rank], hashed[at], tf[at]
    del at
    terms = np.unique(hashed)
    term = np.searchsorted(terms, hashed).astype(np.int32)
    del hashed
    row = np.repeat(np.arange(len(names), dtype=np.int32), sizes)
    start = np.concatenate([[0], np.cumsum(sizes)])
    n = docs.count()
    frequencies = common.materialize(document_frequencies(docs), "frequencies").where(F.col("df") > max(1.0, n * RAREST)).toArrow()
    words, counts = (frequencies[c].to_numpy() for c in ("term", "df"))
    order = np.argsort(words)
    weighting = Weighting(n, words[order], counts[order], terms, relevances(row, term, y, len(terms)))
    del frequencies, words, counts
    weight = np.empty(len(term), np.float32)
    for i in range(0, len(names), 1000):
        some = slice(start[i], start[min(i + 1000, len(names))])
        weight[some] = weighting.unit(row[some] - i, terms[term[some]], tf[some], 1000)[3]
    vectors_ = start, term, weight
    got = [float((y == v).sum()) for v in (0, 1)]
    worth = np.array([size.get(v, 0.0) / max(1.0, got[v]) for v in (0, 1)])
    worth /= max(worth.max(), 1e-9)
    prior = size.get(1, 0.0) / max(1.0, sum(size.values()))
    mass = [worth[v] * float(((sizes == 0) & (y == v)).sum()) for v in (0, 1)]
    empty = (mass[1] + prior) / (sum(mass) + 1) if len(names) else prior
    often = np.argsort(-np.bincount(term, minlength=len(terms)), kind="stable")[:FREQUENT]
    column = np.full(len(terms), -1, np.int32)
    column[often] = np.arange(len(often))
    order = np.lexsort(leading(row, column[term], tf, len(names)))
    common.free()
    return Judge(weighting, names, y, vectors_, order, worth, prior, empty, k)


def calibrated(spark: SparkSession, judge: Judge, model: common.Shared) -> tuple[float, float]:
    """Slope and offset of the logistic curve, from the votes that examples get from all others."""
    if len(set(judge.label.tolist())) < 2:
        return 1.0, 0.0
    picked = judge.picked()

    def run(batches):
        judge = model.value
        picked = judge.picked()
        for batch in batches:
            for b in batch.column(0).to_pylist():
                some = picked[b * BATCH : (b + 1) * BATCH]
                yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(judge.votes(some))], ["i", "v"])

    parts = -(-len(picked) // BATCH)
    rows = common.mapped(spark.range(0, parts, 1, min(parts, common.partitions(spark))), run, "i long, v double").toPandas().sort_values("i")
    y = judge.label[rows["i"].to_numpy()]
    return fit_logistic(logit(rows["v"].to_numpy()), y, judge.worth[y])


def score(docs: DataFrame, labels: DataFrame, label: str = "toxic", held_out=None, examples: int = EXAMPLES, k: int = NEIGHBOURS) -> DataFrame:
    """doc_id, score (calibrated probability of label 1), evidence (ids of the nearest examples, nearest first).

    Learns from label rows outside `held_out` (a condition on doc_id). Texts that are null, empty or without any word get
    what the examples without words say. Without examples of both labels the score is the base rate (0 if there are none).
    Repeated and null ids are kept; an empty table gives no rows.
    """
    judge = learned(docs, labels, label, F.lit(False) if held_out is None else held_out, examples, k)
    model = common.broadcast_of(docs.sparkSession, judge)
    slope, offset = calibrated(docs.sparkSession, judge, model)

    def run(batches):
        import xxhash

        common.reuse_memory()
        judge, seen = model.value, {}
        for batch in batches:
            texts = common.raw(batch.column(1))
            for i, j in common.pieces(texts, 2 << 20):
                for at in range(i, j, 4096):
                    some = texts[at : min(at + 4096, j)]
                    marks = [xxhash.xxh3_128_digest(t) for t in some]
                    new = {m: t for m, t in zip(marks, some, strict=True) if m not in seen}
                    if len(seen) + len(new) > 50_000:
                        seen, new = {}, dict(zip(marks, some, strict=True))
                    scores, near = judge.scores(list(new.values()), slope, offset)
                    for m, s, e in zip(new, scores.tolist(), near.tolist(), strict=True):
                        seen[m] = s, [int(judge.names[x]) for x in e if x >= 0]
                    out = [seen[m] for m in marks]
                    names = batch.column(0).slice(at, len(some))
                    yield pa.RecordBatch.from_arrays([names, pa.array([s for s, _ in out], pa.float64()), pa.array([e for _, e in out], pa.list_(pa.int64()))], ["doc_id", "score", "evidence"])

    return common.mapped(common.texts(docs), run, "doc_id long, score double, evidence array<bigint>")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = common.remainder(4) == 2
    scored = score(common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "labels"), "toxic", out)
    return scored.select("doc_id", out.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"), "evidence")
