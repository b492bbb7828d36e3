"""Shared helpers: table access, shared checkpoints, vectorised word hashing."""

from __future__ import annotations

import ctypes
import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evograph.session import ship

#: Text handled at once inside a Python worker; memory is a small multiple of it.
SLICE_BYTES = 1 << 20
#: How actions of many rounds run: short descriptions of plans, and shuffle files that go with the action.
_ROUNDS = {"spark.sql.maxPlanStringLength": "4096", "spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}
ARROW_ROWS = 1024

_U = np.uint64
#: ASCII white space of the word pattern ``[^\x20\x09-\x0D]+``.
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_BASE = _U(0x9E3779B97F4A7C15)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    # whole texts are wide rows: smaller Arrow batches bound what a JVM and its workers hold
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) > ARROW_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoints(spark: SparkSession) -> None:
    """Use the folder the cluster names in ``spark.checkpoint.dir``.

    A folder of our own is made only where that setting is absent and all is one process, as in tests.
    """
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return
    folder = sc.getConf().get("spark.checkpoint.dir")
    if not folder and not sc.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="evograph-checkpoint-"))


@contextmanager
def _lightly(spark: SparkSession) -> Iterator[None]:
    """Plans made in here leave little behind once they have run.

    The driver keeps a description of every plan it has run, anew for each stage that is
    re-planned; many rounds would fill its memory with them. Shuffle files stay until the driver
    happens to collect its garbage; each map task of each round holds a few blocks of disk.
    """
    usual = {k: spark.conf.get(k, None) for k in _ROUNDS}
    for k, v in _ROUNDS.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in usual.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def cut(df: DataFrame) -> DataFrame:
    """Cut lineage with a reliable checkpoint; lost executors do not lose it."""
    ensure_checkpoints(df.sparkSession)
    with _lightly(df.sparkSession):
        own = df.select("*")  # the settings of a plan are read when it is made
        return _unsized(own.checkpoint(eager=True))


def is_empty(df: DataFrame) -> bool:
    with _lightly(df.sparkSession):
        return df.isEmpty()


def _unsized(df: DataFrame) -> DataFrame:
    """A checkpointed table without the size that was estimated for its plan.

    A join's estimate is the product of those of its sides, and a checkpoint hands it on: a row of
    rounds that join a table with itself doubles the digits in each, and after some thirty joins
    every node of every plan on the driver holds numbers of megabytes.
    """
    spark = df.sparkSession
    jvm, p = spark.sparkContext._jvm, df._jdf.queryExecution().analyzed()
    none = jvm.scala.Option.empty()
    plain = jvm.org.apache.spark.sql.execution.LogicalRDD(p.output(), p.rdd(), p.outputPartitioning(), p.outputOrdering(), p.isStreaming(), p.stream(), spark._jsparkSession, none, none)
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plain), spark)


def forget(df: DataFrame) -> None:
    """Delete the files of a ``cut`` table that nothing will read again."""
    sc = df.sparkSession.sparkContext
    file = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile()
    if file.isDefined():
        path = sc._jvm.org.apache.hadoop.fs.Path(file.get())
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def tidy() -> None:
    """Give freed memory back at the end of a partition: workers live on and other stages follow."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


#: What a worker keeps from one task to the next, by operator.
_KEPT: dict[str, dict] = {}


def kept(owner: str | None = None) -> dict:
    """The tables that a worker keeps for the tasks of ``owner``; what it kept for others is given back first.

    Workers outlive a stage, and an executor's memory must not hold one operator's tables while another one runs.
    """
    others = [k for k in _KEPT if k != owner]
    for k in others:
        _KEPT.pop(k).clear()
    if others:
        tidy()
    return _KEPT.setdefault(owner, {}) if owner else {}


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply), element by element."""
    h = h.copy()
    h ^= h >> _U(30)
    h *= _U(0xBF58476D1CE4E5B9)
    h ^= h >> _U(27)
    h *= _U(0x94D049BB133111EB)
    h ^= h >> _U(31)
    return h


#: Bytes of a chunk that are inside a word, by their number.
_INSIDE = np.array([(1 << (8 * k)) - 1 for k in range(9)], dtype=np.uint64)


def _slice_words(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and 64-bit hash of every word of a byte array.

    A word is chunks of eight bytes; each is mixed with its place before they are added, so
    no arithmetic relation between bytes survives (sums of powers modulo 2^64 would equate
    complementary Thue-Morse words whatever the base).
    """
    word = ~_SPACE[raw]
    edge = np.diff(np.concatenate(([0], word.view(np.int8), [0])))
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    size = ends - starts
    padded = np.concatenate((raw, np.zeros(8, dtype=np.uint8)))
    chunks = np.ndarray(len(raw) + 1, dtype="<u8", buffer=padded, strides=(1,))
    h = mix((chunks[starts] & _INSIDE[np.minimum(size, 8)]) + _BASE)
    long = np.flatnonzero(size > 8)
    if len(long):
        more = (size[long] - 1) // 8  # chunks after the first
        first = np.cumsum(more) - more
        k = np.arange(int(more.sum())) - np.repeat(first, more) + 1
        at = np.repeat(starts[long], more) + 8 * k
        left = np.minimum(np.repeat(ends[long], more) - at, 8)
        h[long] += np.add.reduceat(mix((chunks[at] & _INSIDE[left]) ^ mix(k.astype(np.uint64) * _BASE)), first)
    return starts, ends, mix(h ^ (size.astype(np.uint64) << _U(48)))


def byte_words(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and hash of every word of UTF-8 ``data``, in bounded slices.

    A slice ends on white space, so no word is split; a word longer than a
    slice is taken as one slice of its own.
    """
    raw = np.frombuffer(data, dtype=np.uint8)
    if len(raw) <= 2 * SLICE_BYTES:
        return _slice_words(raw)
    parts, at = [], 0
    while at < len(raw):
        end = min(len(raw), at + SLICE_BYTES)
        while end < len(raw):
            gap = np.flatnonzero(_SPACE[raw[end : end + SLICE_BYTES]])
            if len(gap):
                end += int(gap[0])
                break
            end = min(len(raw), end + SLICE_BYTES)
        s, e, h = _slice_words(raw[at:end])
        parts.append((s + at, e + at, h))
        at = end
    return tuple(np.concatenate(x) for x in zip(*parts))


def slices(texts: list[str | bytes | None]) -> Iterator[tuple[int, int, bytes, np.ndarray]]:
    """Groups of whole texts of about ``SLICE_BYTES``: first row, past row, joined UTF-8, offsets.

    Texts are joined by one newline; ``offsets[k]`` is where text ``k`` of the group starts.
    """
    kept()
    first, size, group = 0, 0, []
    for row, text in enumerate(texts):
        data = text if isinstance(text, bytes) else (text or "").encode("utf-8", "surrogatepass")
        if group and size + len(data) > SLICE_BYTES:
            yield first, row, b"\n".join(group), _offsets(group)
            first, size, group = row, 0, []
        group.append(data)
        size += len(data) + 1
    if group:
        yield first, len(texts), b"\n".join(group), _offsets(group)


def _offsets(group: list[bytes]) -> np.ndarray:
    return np.concatenate(([0], np.cumsum([len(x) + 1 for x in group]))).astype(np.int64)


def words_of_group(data: bytes, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words of a group of texts: start, end, hash, and word offsets by text."""
    s, e, h = byte_words(data)
    return s, e, h, np.searchsorted(s, offsets)


def sequence_hashes(h: np.ndarray, size: int, seed: int = 0) -> np.ndarray:
    """A 64-bit hash of the ``size`` hashes from every position on, for ``len(h) - size + 1`` positions.

    Hashes of doubled stretches are mixed from two halves, and the binary digits of ``size``
    say which stretches make up the whole.
    """
    n = len(h) - size + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    left, right = _U(0xD6E8FEB86659FD93), _U(0xA0761D6478BD642F)
    out, at, span, part = None, 0, 1, mix(h + _U(seed))
    while True:
        if size & span:
            here = part[at : at + n]
            out = here if out is None else mix(out * left + here * right + _U(span))
            at += span
        if 2 * span > size:
            return mix(out ^ _U(size))
        part = mix(part[:-span] * left + part[span:] * right)
        span *= 2


#: Tasks that share the rows of one key in joins.
DEALS = 32


def deal_of(*cols: str) -> Column:
    """One of ``DEALS`` deals, by the columns that tell rows of one key apart."""
    return F.pmod(F.xxhash64(*cols), F.lit(DEALS)).cast("int").alias("deal")


def deals_present() -> Column:
    """Aggregate: the deals that a key's rows are in, as bits."""
    return F.bit_or(F.expr("shiftleft(1L, deal)")).alias("deals")


def by_deal(stats: DataFrame) -> DataFrame:
    """A row for each deal present, to join on key and deal: never more rows than the key has itself."""
    there = F.filter(F.sequence(F.lit(0), F.lit(DEALS - 1)), lambda d: F.getbit("deals", d) == 1)
    return stats.withColumn("deal", F.explode(there)).drop("deals")


def components(links: DataFrame, rounds: int = 64) -> DataFrame:
    """``id, root``: the smallest id that each id of ``links(a, b)`` reaches.

    Alternates two steps until all links lead to roots: every node's larger neighbours are hung on
    its smallest one, then its smaller neighbours are. Rows never exceed the links, and those
    of a node that a third of them share are many tasks' work.
    """
    e = cut(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    for _ in range(rounds):
        ends = e.select(F.col("a").alias("id"), F.lit(1).alias("child"), F.lit(0).alias("parent")).unionByName(e.select(F.col("b").alias("id"), F.lit(0).alias("child"), F.lit(1).alias("parent")))
        ends = ends.groupBy("id").agg(F.sum("child").alias("child"), F.max("parent").alias("parent"))
        if is_empty(ends.where("child > 1 OR (child = 1 AND parent = 1)")):
            return e.select(F.col("a").alias("id"), F.col("b").alias("root"))
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"))).withColumn("deal", deal_of("b"))
        # cut here, too: a plan that holds one self-join inside another is planned eightfold
        large = cut(_with_least(both).where("b > a").select(F.col("b").alias("a"), F.least("a", "m").alias("b")).where("a <> b"))
        small = _with_least(large.withColumn("deal", deal_of("b")))
        last = [e, large]
        e = cut(small.select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct())
        for x in last:
            forget(x)
    raise RuntimeError(f"components: links still change after {rounds} rounds")


def _with_least(e: DataFrame) -> DataFrame:
    """Links with ``m``, the smallest ``b`` of their ``a``."""
    return e.join(by_deal(e.groupBy("a").agg(F.min("b").alias("m"), deals_present())), ["a", "deal"])


def forest(i: np.ndarray, j: np.ndarray, n: int) -> list[tuple[int, int]]:
    """Links that already join what all given links join (union by smaller root)."""
    root = list(range(n))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for x, y in zip(i.tolist(), j.tolist()):
        p, q = find(x), find(y)
        if p != q:
            root[max(p, q)] = min(p, q)
            out.append((x, y))
    return out
