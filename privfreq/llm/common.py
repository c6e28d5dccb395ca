"""What the operators share: tables in the shared folder, whole-text tokens, hashing, Arrow plumbing."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import pickle
import sys
import tempfile
import time
import uuid

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MASK = (1 << 64) - 1


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. A temporary one only in local mode, where the session names none (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = f"file://{tempfile.mkdtemp(prefix='privfreq-')}"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def _made() -> list[list[DataFrame]]:
    # not a global of this module, which travels to the workers by value
    return sys.__dict__.setdefault("_privfreq_made", [])


@contextlib.contextmanager
def temporary():
    """Tables of materialize() made inside are deleted at the end, but for those taken off the list that it gives."""
    _made().append([])
    try:
        yield _made()[-1]
    finally:
        discard(*_made().pop())


#: Rows that go to a Python worker at a time; texts and sets of hashes can be long.
ROWS = 1000


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = ROWS):
    """Queries planned inside hand Arrow batches of fewer rows to Python workers, so that both sides hold less."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back: cuts the lineage, and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with small_batches(spark):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._shared_path = path
    if _made():
        _made()[-1].append(out)
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables of materialize() that nothing reads any more."""
    for df in tables:
        if path := getattr(df, "_shared_path", None):
            jvm = df.sparkSession.sparkContext._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def forget_shuffles(spark: SparkSession) -> None:
    """Let the driver notice which finished queries nothing refers to, so that their shuffle files go."""
    for _ in range(2):  # the first round frees what the second one's finds refer to
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.5)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def texts(docs: DataFrame) -> DataFrame:
    """doc_id and text alone, a null text as the empty one; other columns can't clash."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def remainder(n: int) -> Column:
    """crc32(doc_id as text) mod n; a null id counts as empty text."""
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % n


def raw(column: pa.Array) -> list[bytes]:
    """The texts of an Arrow column as UTF-8."""
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def words(text: bytes) -> list[bytes]:
    """A-Z lower-cased; runs without the ASCII white space x20, x09-x0D."""
    return text.lower().split()


def _store() -> dict:
    return sys.__dict__.setdefault("_privfreq_cache", {})


def claim(owner: str) -> None:
    """Called where an operator's code begins in a worker process: what other operators kept there goes."""
    store = _store()
    if store.get("owner") != owner:
        store.clear()
        store["owner"] = owner
        free()


def free() -> None:
    """Give memory that nothing holds back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def reuse_memory() -> None:
    """Let this process keep what it frees for its next arrays, until free(): for code that makes large ones all the time."""
    with contextlib.suppress(OSError, AttributeError):
        libc = ctypes.CDLL("libc.so.6")
        libc.mallopt(-1, 192 << 20)  # M_TRIM_THRESHOLD
        libc.mallopt(-3, 32 << 20)  # M_MMAP_THRESHOLD


def mapped(df: DataFrame, run, schema: str) -> DataFrame:
    """df.mapInArrow, in workers that keep nothing of other operators, and little between tasks."""
    owner = run.__module__

    def whole(batches):
        claim(owner)
        yield from run(batches)
        free()

    return df.mapInArrow(whole, schema)


def process_cache(key: str, make):
    """One object for each worker process, kept across the tasks of one operator."""
    store = _store()
    if key not in store:
        store[key] = make()
    return store[key]


class Keyed(dict):
    """word -> 64-bit hash, computed once for each word; emptied when it holds too many."""

    limit = 250_000

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= self.limit:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer (fixed values: the multipliers of the public splitmix64 finaliser)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: A random number for each byte, and the base of the polynomial in which a word's hash has them as coefficients.
_BYTE = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BASE = np.uint64(0xD1342543DE82EF95)


def word_hashes(texts: list[bytes], edges: bytes = b"") -> tuple[np.ndarray, np.ndarray]:
    """Text number and 64-bit hash of every word (see words()), in order; without the signs `edges` at either end.

    Words of such signs alone are none. All words are hashed together; hand in a megabyte or so at a time.
    """
    data = np.frombuffer(b"\n".join(texts).lower(), np.uint8)
    kind = np.full(256, 2, np.uint8)
    kind[list(edges)] = 1
    kind[[32, 9, 10, 11, 12, 13]] = 0
    kind = kind[data]
    solid = np.flatnonzero(kind == 2)
    if not len(solid):
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    inside = kind > 0
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    word = np.cumsum(begins)[solid]
    new = np.flatnonzero(np.diff(word, prepend=0))
    first = solid[new]
    length = np.append(solid[new[1:] - 1], solid[-1]) - first + 1
    start = np.cumsum(length) - length
    place = np.arange(int(length.sum())) - np.repeat(start, length)
    powers = np.cumprod(np.concatenate([[np.uint64(1)], np.full(int(length.max()) - 1, _BASE)]), dtype=np.uint64)
    values = _BYTE[data[place + np.repeat(first, length)]] * powers[place]
    begin = np.cumsum([0] + [len(t) + 1 for t in texts[:-1]])
    return np.searchsorted(begin, first, "right") - 1, mix(np.add.reduceat(values, start))


def pieces(texts: list[bytes], size: int = 1 << 20):
    """(from, to) for runs of texts of about `size` bytes; a longer text stands alone."""
    at, n = 0, 0
    for i, t in enumerate(texts):
        if i > at and n + len(t) > size:
            yield at, i
            at, n = i, 0
        n += len(t)
    if at < len(texts):
        yield at, len(texts)


def shingles(tokens: list[bytes], width: int, keyed: Keyed) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the runs of `width` words; fewer words are one run, none give none."""
    n = len(tokens)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(keyed.__getitem__, tokens), np.uint64, n)
    span = min(n, width)
    out = np.full(n - span + 1, span, np.uint64)
    for i in range(span):
        out = mix(out * np.uint64(0x9E3779B97F4A7C15) + h[i : n - span + 1 + i])
    return np.unique(out)


class Shared:
    """A broadcast whose value travels by cloudpickle, as functions do; the newest stays unpacked in each worker process."""

    def __init__(self, spark: SparkSession, value):
        self.name = uuid.uuid4().hex
        self.sent = spark.sparkContext.broadcast(cloudpickle.dumps(value))

    @property
    def value(self):
        held = process_cache("shared", dict)
        if self.name not in held:
            held.clear()
            held[self.name] = pickle.loads(self.sent.value)
            self.sent.__dict__.pop("_value", None)  # the packed form is read again where it is needed
        return held[self.name]


def broadcast_of(spark: SparkSession, value) -> Shared:
    return Shared(spark, value)
