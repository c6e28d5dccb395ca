"""Quality by Bradley-Terry ranking: a linear score learnt from preference pairs, cut at a quantile of all scores.

A pair takes a labelled good and a labelled bad document; the chance that the good one wins is the logistic function of
the difference of their scores, so the loss is logistic in the feature differences. The features are counts of the whole
text. The cut is a quantile of the scores of the whole corpus, found by counting; its level is given, or else the share of
the corpus below the score that splits the labelled examples best.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .toxicity import chosen_examples, fit_logistic

#: Labelled rows of each label, and preference pairs, that the fit may use.
EXAMPLES, PAIRS = 6000, 60_000
RIDGE, BAR = 1e-3, 0.3
UPPER = bytes(range(65, 91))
DIGITS = bytes(range(48, 58))
SIGNS = b"!&%$#*|@<>{}[]()=+\\/^~`_\"'-"
STOPS = b".,;:?"
FEATURES = ("log_words", "word_length", "upper", "digits", "signs", "stops", "bang", "distinct", "top_share", "runs", "line_repeats", "bigram_distinct", "lone_signs", "shout", "long_words")


def features(text: bytes) -> list[float]:
    """Shares and logs over the whole text; an empty text gives zeros."""
    n = len(text)
    words = text.split()
    if not words:
        return [0.0] * len(FEATURES)
    m = len(words)
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    lines = [x for x in text.split(b"\n") if x]
    share = lambda chars: (n - len(text.translate(None, chars))) / n
    signs = share(SIGNS)
    signed = sum(w[-1] in SIGNS for w in words) / m
    shout = sum(map(bytes.isupper, words)) / m
    return [
        np.log1p(m),
        min(n / m, 40.0) / 10,
        share(UPPER),
        share(DIGITS),
        signs,
        share(STOPS),
        text.count(b"!") / n,
        len(counts) / m**0.8,
        max(counts.values()) / m,
        sum(a == b for a, b in zip(words, words[1:])) / m,
        1 - len(set(lines)) / len(lines),
        len(set(zip(words, words[1:]))) / max(1, m - 1) if m > 1 else 1.0,
        signed,
        shout,
        sum(len(w) > 25 for w in words) / m,
    ]


def bend(x: np.ndarray) -> np.ndarray:
    """The features with their square roots: most matter as soon as they are not nothing."""
    return np.hstack([x, np.sqrt(np.maximum(x, 0))])


def fit_pairs(difference: np.ndarray, rounds: int = 30) -> np.ndarray:
    """Weights w that minimise mean log(1+exp(-w.d)) + ridge, by damped Newton steps."""
    n, d = difference.shape
    w = np.zeros(d)

    def loss(w):
        return np.logaddexp(0, -difference @ w).mean() + RIDGE / 2 * w @ w

    for _ in range(rounds):
        p = 1 / (1 + np.exp(np.clip(difference @ w, -30, 30)))
        gradient = -(difference * p[:, None]).mean(0) + RIDGE * w
        hessian = (difference * (p * (1 - p))[:, None]).T @ difference / n + RIDGE * np.eye(d)
        step, size, now = np.linalg.solve(hessian, gradient), 1.0, loss(w)
        while loss(w - size * step) > now and size > 1e-4:
            size /= 2
        w = w - size * step
        if abs(step).max() * size < 1e-7:
            break
    return w


def order_statistics(df: DataFrame, column: str, rank: int, bins: int = 1024) -> tuple[float, float]:
    """The values of this rank (from 1) and of the next in falling-free order, exactly, by counting in ever finer bins.

    Each pass brings `bins` rows to the driver and narrows the range to one bin, whose own ends bound the next pass.
    """
    value = F.col(column)
    ends = df.agg(F.min(value).alias("lo"), F.max(value).alias("hi")).first()
    low, high, below = ends["lo"], ends["hi"], 0
    while low < high:
        width = (high - low) / bins
        place = F.least(F.floor((value - F.lit(low)) / F.lit(width)), F.lit(bins - 1)) if width > 0 else (value > F.lit(low)).cast("int")
        rows = df.where(value.between(low, high)).groupBy(place.alias("b")).agg(F.count("*").alias("n"), F.min(value).alias("lo"), F.max(value).alias("hi")).orderBy("b").collect()
        for i, r in enumerate(rows):
            if below + r["n"] >= rank:
                break
            below += r["n"]
        if below + r["n"] == rank or r["lo"] == r["hi"]:  # the bin's end is the value; the next one may be in another bin
            above = df.where(value > F.lit(r["hi"])).agg(F.min(value)).first()[0]
            return r["hi"], r["hi"] if below + r["n"] > rank or above is None else above
        low, high = r["lo"], r["hi"]
    return low, low


def score(docs: DataFrame, labels: DataFrame, label: str = "quality", held_out=None, examples: int = EXAMPLES, pairs: int = PAIRS, level: float | None = None) -> DataFrame:
    """doc_id, score (0 to 1; 0.3 at the cut), higher for label 1, and level: the share of the corpus below the cut.

    level: that share, if it is to be so; otherwise the one that splits the labelled examples best. Learns from label rows outside `held_out`. Null and empty texts are scored as texts without words. Without examples of
    both labels every score is 1 (nothing is known against a document). Repeated and null ids are kept; an empty table
    gives no rows.
    """
    spark = docs.sparkSession
    held_out = F.lit(False) if held_out is None else held_out
    chosen, size = chosen_examples(labels, label, held_out, examples)

    def measure(batches):
        for batch in batches:
            rows = [features(x) for x in common.raw(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.float64()))], ["doc_id", "x"])

    table = common.materialize(common.mapped(common.texts(docs), measure, "doc_id long, x array<double>"), "quality")
    learned = table.join(F.broadcast(common.materialize(chosen, "examples")), "doc_id").groupBy("doc_id").agg(F.min(F.struct("x", "label")).alias("r")).collect()
    learned.sort(key=lambda r: r["doc_id"])
    y = np.array([r["r"]["label"] for r in learned], np.int64)
    if len(set(y.tolist())) < 2:
        return table.select("doc_id", F.lit(1.0).alias("score"), F.lit(0.0).alias("level"))
    x = bend(np.array([r["r"]["x"] for r in learned], float))
    center, scale = x.mean(0), x.std(0) + 1e-9
    z = (x - center) / scale
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    n = min(pairs, len(good) * len(bad))
    random = np.random.default_rng(7)
    w = fit_pairs(z[random.choice(good, n)] - z[random.choice(bad, n)])
    model = common.broadcast_of(spark, (center, scale, w))

    def rank(batches):
        center, scale, w = model.value
        for batch in batches:
            flat = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(batch), -1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(((bend(flat) - center) / scale) @ w)], ["doc_id", "rank_score"])

    ranked = common.mapped(table, rank, "doc_id long, rank_score double")
    # the level: that of the cut which splits the examples best, both labels weighing alike
    s = z @ w
    order = np.sort(s)
    at = (order[1:] + order[:-1]) / 2
    right = (1 - np.searchsorted(np.sort(s[good]), at) / len(good)) + np.searchsorted(np.sort(s[bad]), at) / len(bad)
    best = np.flatnonzero(right >= right.max() - 1e-9)
    cut = float(at[best].mean())
    sides = ranked.agg(F.max(F.when(F.col("rank_score") < cut, F.col("rank_score"))).alias("below"), F.min(F.when(F.col("rank_score") >= cut, F.col("rank_score"))).alias("above")).first()
    ranked = common.materialize(ranked, "ranked")
    count = ranked.agg(F.count("*").alias("n"), F.count_if(F.col("rank_score") < cut).alias("below")).first()
    rank = count["below"] if level is None else int(np.ceil(level * count["n"]))
    rank = min(max(rank, 0), count["n"])
    if not count["n"]:
        threshold = cut
    elif rank == 0:
        threshold = min(cut, ranked.agg(F.min("rank_score")).first()[0])
    else:
        threshold = float(np.mean(order_statistics(ranked, "rank_score", rank)))
    weight = np.where(y == 1, size.get(1, 1.0) / len(good), size.get(0, 1.0) / len(bad))
    slope, _ = fit_logistic(s - threshold, y, weight / weight.max())
    base = float(np.log(BAR / (1 - BAR)))
    return ranked.select("doc_id", (1 / (1 + F.exp(-(F.lit(slope) * (F.col("rank_score") - F.lit(float(threshold))) + F.lit(base))))).alias("score"), F.lit(rank / max(1, count["n"])).alias("level"))


def op6_quality_ranking(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = common.remainder(5) == 0
    scored = score(common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "labels"), "quality", out)
    return scored.select("doc_id", out.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"), "level")
