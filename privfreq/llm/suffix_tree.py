"""Language-model scores by a probabilistic suffix tree over words, with add-one word counts as its root.

A text is its words (A-Z lower-cased) and one end; the alphabet has the training words, the end, and one sign for every
other word, as the add-one base has. The tree's states are contexts of up to DEPTH words (a text's start is one as well).
A context stays if it was seen MIN_COUNT times, whatever the size of the corpus, and its next-word distribution diverges
from its suffix's: leaving one occurrence out at a time, its words must be likelier under it by more than half a log of
its count. Next words seen MIN_COUNT times get their share less a discount; what is left goes to the suffix's
distribution, down to the root. A word is scored by the longest states of what stands before it.

Nothing of the tree comes to the driver. Texts that are read one after another make groups of bounded size, compressed in
a row each. A group asks for the corpus's counts of its own distinct runs of words, once each, as the compressed
differences of sorted hashes; a bucket (a range of hashes) adds up what all groups sent and answers every group in its
own order, so that neither side joins rows. One round asks for
words and pairs, each further one for runs a word longer (only those that can occur twice, so the tree grows level by
level) and for what decides on the contexts of the round before: sums over a context's occurrences, whichever groups
hold them. The last round scores. A group holds a run once, so a run that a third of all rows have is no larger than others.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Longest context in words, how often it and its next words must be seen, and what is taken off the latter's counts.
DEPTH, MIN_COUNT, DISCOUNT = 2, 2, 0.75
#: Bytes of text in a group, and in a bucket's share of the corpus, about.
GROUP, BUCKET = 6_000_000, 16_000_000
#: Bits of a hash of a word and of a longer run; the first FEWEST tell the smallest bucket.
WORD_BITS, RUN_BITS, FEWEST = 54, 46, 6
_K = np.uint64(0x9E3779B97F4A7C15)
START, END = np.uint64(1), np.uint64(2)  # a word's hash is one of them by a chance of 2^-53

GROUPS = "grp long, n_bytes long, train long, doc_ids array<bigint>, held_out array<boolean>, sizes array<int>, texts binary"
ASKS = "bucket int, grp long, level int, keys binary, sums binary"
ANSWERS = "grp long, level int, bucket int, sums binary"
SCORED = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double"


def bits(level: int) -> int:
    """Bits of the keys of a level: runs of level+1 words, or contexts of -level words."""
    return WORD_BITS if level in (0, -1) else RUN_BITS


def squeezed(values: np.ndarray) -> bytes:
    """The rows of an array: bytes of the same place stand together, compressed."""
    planes = np.frombuffer(values.tobytes(), np.uint8).reshape(len(values), values.dtype.itemsize * int(np.prod(values.shape[1:]))).T
    return len(values).to_bytes(4, "little") + pa.compress(planes.tobytes(), "zstd", asbytes=True)


def expanded(data: bytes, kind: str, columns: int = 1) -> np.ndarray:
    n, width = int.from_bytes(data[:4], "little"), np.dtype(kind).itemsize * columns
    planes = np.frombuffer(pa.decompress(data[4:], n * width, "zstd", asbytes=True), np.uint8)
    values = np.ascontiguousarray(planes.reshape(width, n).T).view(kind)
    return values.ravel() if columns == 1 else values


def packed(keys: np.ndarray, level: int) -> bytes:
    """Sorted keys as their differences."""
    return squeezed(np.diff(keys, prepend=np.uint64(0)).astype("<u8"))


def unpacked(data: bytes, level: int, bucket: int, buckets: int) -> np.ndarray:
    return np.cumsum(expanded(data, "<u8"), dtype=np.uint64)


def run_hashes(before: np.ndarray, token: np.ndarray) -> np.ndarray:
    """Hashes of runs: of what a context is, and the word after it."""
    return common.mix(before * _K + token) >> np.uint64(64 - RUN_BITS)


class Group:
    """The tokens of some texts, and what is known of the runs that end in each, level by level.

    answers: for a level (runs of level+1 words) the corpus's counts of its distinct keys; for -level what contexts of
    that many words leave to their suffixes (0: no state). learns: whether a text is a training text.
    """

    def __init__(self, texts: list[bytes], learns: np.ndarray, answers: dict[int, np.ndarray], tokens: int = 1, kinds: int = 0, training: int = 0):
        self.texts, self.answers, self.total, self.training = len(texts), answers, tokens + kinds + 1, training
        rows, words = [np.arange(self.texts)], [np.full(self.texts, END)]
        for i, j in common.pieces(texts):
            row, h = common.word_hashes(texts[i:j])
            rows.append(row + i)
            words.append(h >> np.uint64(64 - WORD_BITS))
        row = np.concatenate([*rows[1:], rows[0]])
        order = np.argsort(row, kind="stable")
        self.row, self.token = row[order], np.concatenate([*words[1:], words[0]])[order]
        self.n_tokens = np.bincount(self.row, minlength=self.texts)
        self.first = np.cumsum(self.n_tokens) - self.n_tokens
        self.learns = learns[self.row]
        self.keys: dict[int, np.ndarray] = {}
        self.counts: dict[int, np.ndarray] = {}
        self.distinct: dict[int, tuple] = {}

    def behind(self, values: np.ndarray, start) -> np.ndarray:
        """What stands one token earlier; start for a text's first token."""
        out = np.empty_like(values)
        out[1:] = values[:-1]
        out[self.first] = start
        return out

    def runs(self, level: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places whose run of level+1 words is looked at, its distinct hashes, and which of them each place has."""
        if level not in self.distinct:
            if level == 0:
                self.keys[0], places = self.token, np.arange(len(self.token))
            else:
                self.runs(level - 1)
                before = self.behind(self.keys[level - 1], START if level == 1 else np.uint64(0))
                self.keys[level] = run_hashes(before, self.token)
                places = np.arange(len(self.token))
                if level > 1:  # both runs that are a word shorter must occur twice
                    often = self.count(level - 1) >= MIN_COUNT
                    places = np.flatnonzero(often & self.behind(often, False))
            self.distinct[level] = places, *np.unique(self.keys[level][places], return_inverse=True)
        return self.distinct[level]

    def count(self, level: int) -> np.ndarray:
        """How often the run that ends at each place occurs in training texts (0 where it was not looked at)."""
        if level not in self.counts:
            places, _, of = self.runs(level)
            self.counts[level] = np.zeros(len(self.token), np.int64)
            self.counts[level][places] = self.answers[level][of]
        return self.counts[level]

    def context_count(self, level: int) -> np.ndarray:
        """How often the `level` words before each place occur in training texts."""
        return self.behind(self.count(level - 1), self.training if level == 1 else 0)

    def contexts(self, level: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places after a context that was seen often enough, the distinct contexts, and which of them each place has."""
        if -level not in self.distinct:
            self.count(level - 1)
            places = np.flatnonzero(self.context_count(level) >= MIN_COUNT)
            before = self.behind(self.keys[level - 1], START if level == 1 else np.uint64(0))
            self.distinct[-level] = places, *np.unique(before[places], return_inverse=True)
        return self.distinct[-level]

    def probability(self, level: int) -> np.ndarray:
        """Of every token after the states of up to `level` words."""
        if level == 0:
            return (self.count(0) + 1) / self.total
        out = self.probability(level - 1)
        places, _, of = self.contexts(level)
        rest = self.answers[-level][of]
        n, c = self.context_count(level)[places].astype(float), self.count(level)[places]
        own = np.where(c >= MIN_COUNT, (c - DISCOUNT) / n, 0.0)
        out[places] = np.where(rest > 0, own + rest * out[places], out[places])
        return out

    def ask_runs(self, level: int) -> tuple[np.ndarray, np.ndarray]:
        places, keys, of = self.runs(level)
        return keys, np.bincount(of, self.learns[places], len(keys)).astype(np.int64)

    def ask_contexts(self, level: int) -> tuple[np.ndarray, np.ndarray]:
        """For each context: what its frequent next words take of its occurrences, by how much it makes them likelier with
        one occurrence left out (natural log, at least), how many occurrences they are; and its count, alike in all groups."""
        places, keys, of = self.contexts(level)
        c, n = self.count(level)[places], self.context_count(level)[places]
        seen = np.zeros(len(keys))
        seen[of] = n
        use = np.flatnonzero(self.learns[places] & (c >= MIN_COUNT))
        c, n, of = c[use].astype(float), n[use], of[use]
        without = self.probability(level - 1)[places][use]
        gain = np.log((c - 1 - DISCOUNT) / (n - 1) / without)
        sums = [np.bincount(of, v, len(keys)) for v in ((c - DISCOUNT) / c, gain, np.ones(len(c)))]
        return keys, np.column_stack([*sums, seen])

    def scores(self, depth: int) -> tuple[np.ndarray, ...]:
        """n_tokens, n_known, base, score of every text (log10)."""
        add = lambda x: np.bincount(self.row, x, self.texts)
        known = self.count(0) > 0
        return self.n_tokens, add(known).astype(np.int64), add(np.log10(self.probability(0))), add(np.log10(self.probability(depth)))


def asked(group: Group, number: int, level: int, buckets: int):
    """The rows of ASKS of a group: its keys are sorted, so a bucket has a slice of them."""
    keys, sums = group.ask_runs(level) if level >= 0 else group.ask_contexts(-level)
    sums = sums.astype("<f4") if level < 0 else sums.astype("<u4")
    cuts = np.searchsorted(keys, np.arange(1, buckets, dtype=np.uint64) << np.uint64(bits(level) - (buckets.bit_length() - 1)))
    for bucket, (i, j) in enumerate(zip([0, *cuts], [*cuts, len(keys)], strict=True)):
        if i < j:
            yield bucket, number, level, packed(keys[i:j], level), squeezed(sums[i:j])


def left(taken: np.ndarray, gain: np.ndarray, often: np.ndarray, n: np.ndarray) -> np.ndarray:
    """What contexts that stay leave to their suffixes; 0 for those that go."""
    rest = np.clip(1 - taken / n, 1e-9, 1.0)
    return np.where((taken > 0) & (gain + (n - often) * np.log(rest) > np.log(n) / 2), rest, 0.0)


def answered(table: pa.Table, buckets: int) -> pa.Table:
    """Rows of ANSWERS to the asks of one bucket and level; group -1 gets how many keys were counted, and their sum."""
    rows = sorted(table.to_pylist(), key=lambda r: r["grp"])
    bucket, level = rows[0]["bucket"], rows[0]["level"]
    parts = [unpacked(r["keys"], level, bucket, buckets) for r in rows]
    keys, of = np.unique(np.concatenate(parts), return_inverse=True)
    if level < 0:
        sums = np.concatenate([expanded(r["sums"], "<f4", 4) for r in rows])
        n = np.zeros(len(keys))
        n[of] = sums[:, 3]
        total = left(*(np.bincount(of, sums[:, i], len(keys)) for i in range(3)), n).astype("<f4")
        facts = np.zeros(2)
    else:
        total = np.bincount(of, np.concatenate([expanded(r["sums"], "<u4") for r in rows]), len(keys)).astype("<u4")
        facts = np.array([(total > 0).sum(), total.sum(dtype=np.float64)])
    out = {"grp": [-1], "level": [level], "bucket": [bucket], "sums": [facts.tobytes()]}
    at = 0
    for r, part in zip(rows, parts, strict=True):
        for name, value in (("grp", r["grp"]), ("level", level), ("bucket", bucket), ("sums", squeezed(total[of[at : at + len(part)]]))):
            out[name].append(value)
        at += len(part)
    return pa.table({"grp": pa.array(out["grp"], pa.int64()), "level": pa.array(out["level"], pa.int32()), "bucket": pa.array(out["bucket"], pa.int32()), "sums": pa.array(out["sums"], pa.binary())})


def collected(answers: pa.Table | None) -> dict[int, np.ndarray]:
    """The answers of one group by level, in the order of its keys."""
    out: dict[int, list] = {}
    rows = [] if answers is None else answers.select(["level", "bucket", "sums"]).to_pylist()
    for r in sorted(rows, key=lambda r: r["bucket"]):
        out.setdefault(r["level"], []).append(expanded(r["sums"], "<f4" if r["level"] < 0 else "<u4"))
    return {level: np.concatenate(parts).astype(np.float64 if level < 0 else np.int64) for level, parts in out.items()}


def grouped(rows: DataFrame, group_bytes: int) -> DataFrame:
    """GROUPS of rows (doc_id, text, held_out): texts read one after another, up to group_bytes of them (a longer one stands alone).

    Nothing is dealt by a key, so neither repeated texts nor repeated ids gather.
    """

    def run(batches):
        from pyspark import TaskContext

        number, held, n = TaskContext.get().partitionId() << 32, [], 0

        def row():
            ids, texts, out = (list(x) for x in zip(*held, strict=True))
            values = [[number], [n], [out.count(False)], [ids], [out], [[len(t) for t in texts]], [pa.compress(b"".join(texts), "zstd", asbytes=True)]]
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.int32()), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(values, kinds, strict=True)], [c.split()[0] for c in GROUPS.split(", ")])

        for batch in batches:
            for item in zip(batch.column(0).to_pylist(), common.raw(batch.column(1)), batch.column(2).to_pylist(), strict=True):
                if held and n + len(item[1]) > group_bytes:
                    yield row()
                    number, held, n = number + 1, [], 0
                held.append(item)
                n += len(item[1])
        if held:
            yield row()

    return common.mapped(rows, run, GROUPS)


def texts_of(row: dict) -> list[bytes]:
    ends = np.cumsum(row["sizes"]).tolist()
    whole = pa.decompress(row["texts"], ends[-1], "zstd", asbytes=True)
    return [whole[i:j] for i, j in zip([0, *ends[:-1]], ends, strict=True)]


def text_scores(docs: DataFrame, held_out, depth: int = DEPTH, group_bytes: int = GROUP) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (both log10 of the text's probability).

    Learns from the documents where `held_out` (a condition on doc_id) is false. Null and empty texts are the end alone.
    Words are told apart by hashes of 54 bits, longer runs of 46 (n of them collide n^2/2^47 times). Without any training text every token has probability 1. Repeated and
    null ids are kept; an empty table gives no rows.
    """
    if depth < 1:
        raise ValueError("contexts have one word or more")
    rows = common.texts(docs).select("doc_id", "text", held_out.alias("held_out"))
    rows = common.materialize(grouped(rows, group_bytes), "texts")  # written, so that all readings agree
    size = rows.agg(F.sum("n_bytes").alias("bytes"), F.sum("train").alias("train")).first()
    buckets = 1 << max(FEWEST, (max(1, (size["bytes"] or 0) // BUCKET) - 1).bit_length())
    training = size["train"] or 0

    def opened(row: dict, answers: pa.Table | None, tokens: int, kinds: int) -> Group:
        common.claim(__name__)
        common.reuse_memory()
        return Group(texts_of(row), ~np.array(row["held_out"], bool), collected(answers), tokens, kinds, training)

    def asking(levels: list[int], tokens: int, kinds: int):
        def ask(texts: pa.Table, answers: pa.Table | None) -> pa.Table:
            if not texts.num_rows:
                listed = []
            else:
                row = texts.to_pylist()[0]
                group = opened(row, answers, tokens, kinds)
                listed = [r for level in levels for r in asked(group, row["grp"], level, buckets)]
            kinds_ = (pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary())
            return pa.table({c.split()[0]: pa.array([r[i] for r in listed], kinds_[i]) for i, c in enumerate(ASKS.split(", "))})

        return ask

    def answer(asks: DataFrame) -> DataFrame:
        def solve(table: pa.Table) -> pa.Table:
            common.claim(__name__)
            return answered(table, buckets)

        return common.materialize(asks.groupBy("bucket", "level").applyInArrow(solve, ANSWERS), "answers")

    def both(answers: DataFrame):
        return rows.groupBy("grp").cogroup(answers.where("grp >= 0").groupBy("grp"))

    first = asking([0, 1], 1, 0)
    answers = answer(rows.groupBy("grp").applyInArrow(lambda texts: first(texts, None), ASKS))
    facts = [np.frombuffer(r["sums"]) for r in answers.where("grp = -1 and level = 0").select("sums").toLocalIterator()]
    kinds, tokens = (int(sum(f[i] for f in facts)) for i in (0, 1))
    for d in range(1, depth + 1):
        common.forget_shuffles(docs.sparkSession)
        levels = [-d] + [d + 1] * (d < depth)
        answers = answers.unionByName(answer(both(answers).applyInArrow(asking(levels, tokens, kinds), ASKS)))
    common.forget_shuffles(docs.sparkSession)

    def score(texts: pa.Table, answers_: pa.Table) -> pa.Table:
        names = [c.split()[0] for c in SCORED.split(", ")]
        if not texts.num_rows:
            return pa.table({n: pa.array([], t) for n, t in zip(names, (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64()), strict=True)})
        row = texts.to_pylist()[0]
        got = opened(row, answers_, tokens, kinds).scores(depth)
        return pa.table({"doc_id": pa.array(row["doc_ids"], pa.int64()), "held_out": row["held_out"], **{n: pa.array(v) for n, v in zip(names[2:], got, strict=True)}})

    scored = both(answers).applyInArrow(score, SCORED)
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(tokens).cast("long").alias("train_tokens"), "base_score", "score")


def op7_suffix_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_scores(common.read(spark, sf_dir, "documents"), common.remainder(7) == 2)
