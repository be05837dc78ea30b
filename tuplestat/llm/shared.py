"""What the training-data operators have in common: shared storage, word hashing, name hygiene."""

from __future__ import annotations

import atexit
import ctypes
import gc
import re
import tempfile
import uuid
import weakref

import numpy as np
import pyarrow as pa
from pyspark.errors import PySparkException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_STAGED: dict[str, weakref.ref] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, only a
    session in local mode (one machine, as in tests) gets a folder of its own; on a cluster that
    is an error, since executors would not see it."""
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if sc.getCheckpointDir() is None:
        if not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="tuplestat-ckpt-"))
    return sc.getCheckpointDir().rstrip("/")


def staged(df: DataFrame, tag: str) -> DataFrame:
    """Write `df` as Parquet to the shared folder and read it back.

    This cuts lineage in a way that survives the loss of any executor (unlike localCheckpoint)
    and lets later steps read only the columns they need. Files go away with the session.
    """
    spark = df.sparkSession
    path = staged_path(spark, tag)
    free_shuffles(spark)
    df.write.parquet(path)
    free_shuffles(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path
    return out


def free_shuffles(spark: SparkSession) -> None:
    """Have the shuffle files of finished steps deleted: Spark does so once the driver's collector
    has found their plans unused, which a quiet driver may put off for half an hour."""
    try:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(2000)  # events hold plans too
    except Exception:  # busy for longer, or another version: files go away later
        pass
    spark.sparkContext._jvm.System.gc()


def staged_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder, which goes away with the session or by `discard`."""
    path = f"{shared_dir(spark)}/tuplestat-{tag}-{uuid.uuid4().hex}"
    _STAGED[path] = weakref.ref(spark)
    return path


def discard(df: DataFrame) -> None:
    """Delete the files behind a frame made by `staged` that nothing will read again."""
    if getattr(df, "_staged_path", None) in _STAGED:
        _remove(df.sparkSession, df._staged_path)


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    _STAGED.pop(path, None)


@atexit.register
def _sweep() -> None:
    for path, ref in list(_STAGED.items()):
        spark = ref()
        try:
            if spark is not None and spark.sparkContext._jsc is not None:
                _remove(spark, path)
        except Exception:  # the session is gone already; its owner clears the shared folder
            _STAGED.pop(path, None)


#: Bits of a summary of needed keys: at least MIN_BITS, eight for a key, at most MOST_BITS (64 MB).
MIN_BITS, MOST_BITS = 1 << 20, 1 << 29


class BitMap:
    """Which slots of a power-of-two table some keys fall on; packed, shipped once to each worker."""

    def __init__(self, packed: np.ndarray):
        self.packed = packed
        self.mask = 8 * len(packed) - 1

    def has(self, hashes: np.ndarray) -> np.ndarray:
        """Which of these 64-bit hashes (signed) are in the map; some others pass too."""
        slot = hashes & np.int64(self.mask)
        return ((self.packed[slot >> 3] >> (slot & 7).astype(np.uint8)) & 1).astype(bool)


def bit_map(keys: DataFrame, hashed) -> BitMap | None:
    """The map of `keys` by a 64-bit hash column, sized by their number; None when there are so many
    that even the largest map would hold back little. Callers join exactly afterwards either way."""
    n = keys.count()
    if n > MOST_BITS // 2:
        return None
    bits = min(MOST_BITS, max(MIN_BITS, 1 << (8 * n - 1).bit_length()))
    slot = (hashed.bitwiseAND(F.lit(bits - 1)) + 1).alias("slot")
    rows = (
        keys.select(slot)
        .groupBy(F.bitmap_bucket_number("slot").alias("bucket"))
        .agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("bits"))
        .toLocalIterator()  # at most bits / 32768 rows of 4 KB
    )
    out = np.zeros(bits // 8, dtype=np.uint8)
    for r in rows:
        lo = (r.bucket - 1) * 4096
        out[lo : lo + 4096] |= np.frombuffer(bytes(r.bits), dtype=np.uint8)
    return BitMap(out)


def fresh(columns: list[str], base: str) -> str:
    """A column name that clashes with none of `columns` (case-insensitively, as Spark compares)."""
    taken = {c.lower() for c in columns}
    name = base
    while name.lower() in taken:
        name = f"_{name}"
    return name


def least_hashed(df: DataFrame, n: int, key: str) -> DataFrame:
    """The `n` rows with the least hashes of `key` (all, if fewer). Rows far above are left out first, so
    that the task which picks the rows gets a few times `n` however large the table is."""
    h = F.xxhash64(F.col(key))
    total = df.count()
    if total > 8 * n:
        df = df.where(h < F.lit(-(1 << 63) + int((1 << 64) * (4 * n + 400) / total)))
    return df.orderBy(h, key).limit(n)


BATCH_BYTES = 4 << 20


def bounded_batches(spark: SparkSession, most: int = BATCH_BYTES) -> None:
    """Have Arrow batches end at `most` bytes, besides their bound in rows: rows here may be long
    texts or sets, and a batch is held by both the JVM and the Python worker. A runtime setting."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    try:
        now = int(spark.conf.get(name).lower().removesuffix("b"))
        if now > most or now == BATCH_BYTES:
            spark.conf.set(name, str(most))
    except (ValueError, PySparkException):  # a version without it, or a value with a unit
        return


def id_text(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Only the two columns an operator reads, under fixed names; null texts stay null."""
    bounded_batches(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def thrifty() -> None:
    """Have this worker give freed memory back: workers live on from stage to stage, and what an
    allocator keeps for later adds up on an executor."""
    pa.default_memory_pool().release_unused()
    if "c" not in _LIBRARY:
        _LIBRARY["c"] = None
        try:
            _LIBRARY["c"] = ctypes.CDLL(None)
            for option, value in ((-1, 4 << 20), (-3, 4 << 20), (-8, 2)):  # trim and map thresholds, arenas
                _LIBRARY["c"].mallopt(option, value)
        except (OSError, AttributeError):  # another C library
            pass
    try:
        _LIBRARY["c"].malloc_trim(0)
    except AttributeError:
        pass


_LIBRARY: dict = {}


def slices(batches, bytes_per_slice: int = 2 << 20):
    """Re-cut Arrow batches so that a slice holds about `bytes_per_slice` of data (one row at least)."""
    thrifty()
    for batch in batches:
        n = batch.num_rows
        if n == 0:
            continue
        step = max(1, min(n, int(n * bytes_per_slice / max(batch.nbytes, 1))))
        at = 0
        while at < n:
            part = batch.slice(at, step)
            yield part
            at += step


_HELD: dict = {}


def held(key, make):
    """`make()`, kept by this worker process until another key is asked for: one operator's
    tables at a time, since workers live on and their memory adds up."""
    if key not in _HELD:
        if _HELD:
            _HELD.clear()
            gc.collect()
            thrifty()
        _HELD[key] = make()
    return _HELD[key]


def batch_of(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [c if isinstance(c, pa.Array) else pa.array(c, type=f.type) for c, f in zip(columns, schema)], schema=schema
    )


# ---------------------------------------------------------------- vectorised word hashing

_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_GOLD = np.uint64(0x9E3779B97F4A7C15)
_MULT = np.uint64(0xFF51AFD7ED558CCD)
_BASE = 0xD6E8FEB86659FD93
_BASE_INV = pow(_BASE, -1, 1 << 64)
#: Words of up to this many bytes are hashed byte by byte, all words at once.
SHORT = 64


def mix64(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64: a bijection that spreads every bit."""
    with np.errstate(over="ignore"):
        y = x >> np.uint64(30)
        y ^= x
        y *= _M1
        y ^= y >> np.uint64(27)
        y *= _M2
        y ^= y >> np.uint64(31)
        return y


_POWERS = [np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64, grown on demand and kept by the worker."""
    if len(_POWERS[0]) < n:
        size = 1 << (n - 1).bit_length()
        for k, b in enumerate((_BASE, _BASE_INV)):
            p = np.full(size, b, dtype=np.uint64)
            p[0] = 1
            with np.errstate(over="ignore"):
                _POWERS[k] = np.multiply.accumulate(p)
    return _POWERS[0], _POWERS[1]


_TERMS: list[np.ndarray] = []


def _terms() -> list[np.ndarray]:
    """For each place in a short word, what each byte (A-Z lowered) adds to the word's polynomial."""
    if not _TERMS:
        value = lowered(np.arange(256, dtype=np.uint8)).astype(np.uint64) + np.uint64(1)
        with np.errstate(over="ignore"):
            _TERMS.extend(value * p for p in _powers(SHORT)[0][:SHORT])
    return _TERMS


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(UTF-8 bytes of all rows end to end, row offsets); null rows are empty."""
    column = column.fill_null("")
    if pa.types.is_large_string(column.type):
        column = column.cast(pa.string())
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, dtype=np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def is_space(raw: np.ndarray) -> np.ndarray:
    """Which bytes are ASCII white space."""
    return (raw == 32) | ((raw - np.uint8(9)) < 5)


def lowered(raw: np.ndarray) -> np.ndarray:
    """The bytes with A-Z lowered."""
    return raw | (((raw - np.uint8(65)) < 26).view(np.uint8) << np.uint8(5))


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of each maximal run outside ASCII white space, and the row it lies in.

    Rows never share a word: a row's end ends its last word.
    """
    if len(raw) == 0:
        z = np.zeros(0, np.int64)
        return z, z, z
    inside = np.zeros(len(raw) + 2, dtype=bool)
    np.logical_not(is_space(raw), out=inside[1:-1])
    turns = np.flatnonzero(inside[1:] != inside[:-1])  # starts and ends by turns
    starts, ends = turns[::2], turns[1::2]
    inner = np.unique(offsets[1:-1])
    inner = inner[(inner > 0) & (inner < len(raw))]
    cut = inner[inside[inner] & inside[inner + 1]]
    if len(cut):
        starts, ends = np.sort(np.concatenate([starts, cut])), np.sort(np.concatenate([ends, cut]))
    return starts, ends, np.repeat(np.arange(len(offsets) - 1), np.diff(np.searchsorted(starts, offsets)))


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word with A-Z lowered: a polynomial over its bytes, then mixed.

    Words are laid by length, so that those with a byte at a place are a prefix: an array pass
    per place. Words longer than SHORT bytes are laid end to end, summed from the first byte on,
    and made free of their places."""
    n = len(starts)
    if n == 0:
        return np.zeros(0, np.uint64)
    size = ends - starts
    order = np.argsort(-np.minimum(size, SHORT + 1).astype(np.int16), kind="stable")
    begin = starts[order]
    longer = n - np.cumsum(np.bincount(np.minimum(size, SHORT), minlength=SHORT + 1))  # than k bytes
    total = np.zeros(n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k, term in enumerate(_terms()):
            m = int(longer[k])
            if not m:
                break
            total[:m] += term[raw[begin[:m] + k]]
        h = np.empty(n, dtype=np.uint64)
        h[order] = total
        long = np.flatnonzero(size > SHORT)
        if len(long):
            first = np.concatenate([[0], np.cumsum(size[long])])
            power, inverse = _powers(int(first[-1]) + 1)
            low = lowered(raw[np.arange(first[-1]) + np.repeat(starts[long] - first[:-1], size[long])])
            sums = np.zeros(len(low) + 1, dtype=np.uint64)
            np.cumsum((low.astype(np.uint64) + np.uint64(1)) * power[: len(low)], out=sums[1:])
            h[long] = (sums[first[1:]] - sums[first[:-1]]) * inverse[first[:-1]]
        return mix64(h + size.astype(np.uint64) * _GOLD)


def shingle_hashes(column: pa.Array, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed word shingles of each row, flattened, with row offsets.

    A row with fewer words than `size` has its whole sequence as one shingle; one without words
    has none. Hashes are sorted within a row.
    """
    raw, offsets = text_bytes(column)
    n = len(offsets) - 1
    starts, ends, row = word_spans(raw, offsets)
    h = word_hashes(raw, starts, ends)
    count = np.bincount(row, minlength=n) if n else np.zeros(0, np.int64)
    return distinct_shingles(h, count, size)


def distinct_shingles(h: np.ndarray, count: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Same, from the word hashes of consecutive rows and the number of words of each row."""
    n = len(count)
    first = np.concatenate([[0], np.cumsum(count)]).astype(np.int64)
    width = np.minimum(count, size)
    made = np.maximum(count - size + 1, (count > 0).astype(count.dtype)) if n else count
    owner = np.repeat(np.arange(n), made)
    base = np.concatenate([[0], np.cumsum(made)]).astype(np.int64)
    begin = first[owner] + (np.arange(len(owner)) - base[owner])
    wide = width[owner]
    with np.errstate(over="ignore"):
        s = wide.astype(np.uint64) * _GOLD
        for k in range(size):
            here = wide > k
            nxt = h[np.where(here, begin + k, 0)] if len(h) else np.zeros(0, np.uint64)
            s = np.where(here, mix64(s * _MULT + nxt), s)
    order = np.lexsort((s, owner))
    s, owner = s[order], owner[order]
    keep = np.ones(len(s), dtype=bool)
    keep[1:] = (s[1:] != s[:-1]) | (owner[1:] != owner[:-1])
    s, owner = s[keep], owner[keep]
    return s, np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=n))]).astype(np.int64)
