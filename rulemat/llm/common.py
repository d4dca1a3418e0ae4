"""Shared pieces of the corpus operators: table access, shared storage, byte-level
text kernels and a packed exchange.

The kernels look at texts as the UTF-8 bytes that Arrow already holds.  A batch is cut
into slices of a few MB, each slice is one ``uint8`` buffer with document offsets, and
words, shingles and k-grams of a whole slice are found and hashed with array operations.
"""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sharing import shared_root

U64 = np.uint64
#: Bytes of text worked on at once; bounds the temporaries of a task.
SLICE_BYTES = 1 << 18

_ODD = 0x9E3779B97F4A7C15
_SEED = (0xB5026F5AA96619E9, 0xD6E8FEB86659FD93)
_lean = False


def lean_heap() -> None:
    """Make a worker give large buffers back as soon as they are free: by default the C library
    keeps blocks of up to 32 MB and Arrow's pool keeps more, in every idle worker."""
    global _lean
    if _lean:
        return
    _lean = True
    pa.set_memory_pool(pa.system_memory_pool())
    mallopt = getattr(ctypes.CDLL(None), "mallopt", None)
    if mallopt is not None:  # a C library without it has other habits
        mallopt(-3, 1 << 18)  # M_MMAP_THRESHOLD
        mallopt(-1, 1 << 20)  # M_TRIM_THRESHOLD
        mallopt(-8, 2)  # M_ARENA_MAX


def trim_heap() -> None:
    """Give small freed blocks back as well."""
    lean_heap()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def resting(work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``work`` for ``mapInArrow``: its worker, which may wait idle through many stages, holds no
    freed memory after a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from work(batches)
        finally:
            trim_heap()

    return run


#: Documents in an Arrow batch: whole texts travel, so the default of 10,000 rows would hold
#: tens of MB in the JVM and again in each Python worker.
BATCH_ROWS = 1000


def bounded_batches(spark: SparkSession) -> None:
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bounded_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession, what: str) -> str:
    """A fresh folder that driver and executors share."""
    return f"{shared_root(spark)}/{what}-{uuid.uuid4().hex[:12]}"


def persisted(df: DataFrame, what: str) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage, survives lost executors."""
    bounded_batches(df.sparkSession)
    path = shared_dir(df.sparkSession, what)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._shared_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete what ``persisted`` wrote, once no later step reads it."""
    for df in frames:
        path = getattr(df, "_shared_path", None)
        if path:
            spark = df.sparkSession
            jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
            jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def rest_executors(spark: SparkSession) -> None:
    """Make every executor's JVM give back the heap that earlier jobs filled.  By itself it grows
    up to its limit and keeps that, beside the Python workers; a collection on request shrinks it
    to what is in use.  One task a core reaches all executors that wait for work."""
    cores = spark.sparkContext.defaultParallelism
    collected = F.java_method(F.lit("java.lang.System"), F.lit("gc")).alias("collected")
    spark.range(0, cores, 1, cores).select(collected).write.format("noop").mode("overwrite").save()


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def keyed_documents(docs: DataFrame) -> DataFrame:
    """(doc_id, text, key): a key that orders documents and is never null or repeated: doc_id,
    or a number in (doc_id, text) order where some doc_id is missing or repeated."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    odd = docs.groupBy("doc_id").count().where((F.col("count") > 1) | F.col("doc_id").isNull()).limit(1).count()
    if not odd:
        return docs.withColumn("key", F.col("doc_id"))
    return persisted(docs.orderBy("doc_id", "text").withColumn("key", F.monotonically_increasing_id()), "ordered")


# --------------------------------------------------------------------- hashing


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash; a bijection."""
    h = h ^ (h >> U64(30))
    h *= U64(0xBF58476D1CE4E5B9)
    h ^= h >> U64(27)
    h *= U64(0x94D049BB133111EB)
    h ^= h >> U64(31)
    return h


def pair_name(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Name of a pair of names (order matters)."""
    return mix(a * U64(0xC2B2AE3D27D4EB4F) + (b ^ U64(0x165667B19E3779F9)))


#: Keeps the first k bytes of eight.
BYTE_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], dtype=U64)


def unaligned(values: np.ndarray) -> np.ndarray:
    """The eight bytes from every position on as one number; zeros follow the end."""
    padded = np.zeros(len(values) + 8, np.uint8)
    padded[: len(values)] = values
    return np.ndarray((len(values) + 1,), "<u8", padded, strides=(1,))


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, which: int = 0) -> np.ndarray:
    """64-bit hash of each span of a byte array, equal for equal content.

    A span's pieces of eight bytes are mixed with their place in it before they are added up,
    so that no arrangement of equal pieces cancels out, as it can in a polynomial."""
    if not len(starts):
        return np.zeros(0, U64)
    n = ends - starts
    count = np.maximum(1, (n + 7) >> 3)
    stop = np.cumsum(count)
    first, eight, seed = stop - count, unaligned(values), U64(_SEED[which])
    if int(stop[-1]) == len(n):
        total = mix((eight[starts] & BYTE_MASK[n]) ^ mix(np.full(1, seed, U64)))
    else:
        place = np.arange(int(stop[-1])) - np.repeat(first, count)
        at = np.repeat(starts, count) + 8 * place
        left = np.minimum(np.repeat(ends, count) - at, 8)
        total = np.add.reduceat(mix((eight[at] & BYTE_MASK[left]) ^ mix(place.astype(U64) * U64(_ODD) + seed)), first)
    return mix(total + n.astype(U64) * U64(_ODD))


# ----------------------------------------------------------------------- texts


def _lut(ranges: str, out: bool = True) -> np.ndarray:
    lut = np.full(256, not out)
    for part in ranges.split():
        lo, _, hi = part.partition("-")
        lut[int(lo, 16) : int(hi or lo, 16) + 1] = out
    return lut


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Bytes that belong to a word: all but ASCII white space.
NOT_SPACE = _lut("20 09-0D", out=False)
#: Bytes that belong to a word: digits, letters and every byte of a non-ASCII character.
ALNUM = _lut("30-39 61-7A 80-FF")


class Texts:
    """A slice of documents as one byte buffer; ``offs`` has one entry more than there are
    documents, ``first`` is the row of the first one in its batch."""

    __slots__ = ("data", "first", "n", "offs")

    def __init__(self, data: np.ndarray, offs: np.ndarray, first: int = 0):
        self.data, self.offs, self.first, self.n = data, offs, first, len(offs) - 1

    def bytes_of(self, k: int) -> bytes:
        return self.data[self.offs[k] : self.offs[k + 1]].tobytes()


def byte_column(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Buffer and offsets of a string or binary column; nulls are empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = col.fill_null(b"" if pa.types.is_binary(col.type) or pa.types.is_large_binary(col.type) else "")
    wide = col.type in (pa.large_string(), pa.large_binary())
    _, off, data = col.buffers()
    offs = np.frombuffer(off, dtype=np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64) if len(col) else np.zeros(1, np.int64)
    buf = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return buf, offs


def slices(col: pa.Array, budget: int = SLICE_BYTES) -> Iterator[Texts]:
    """Cut a column into slices of about ``budget`` bytes, at document borders."""
    lean_heap()
    buf, offs = byte_column(col)
    n, k = len(offs) - 1, 0
    while k < n:
        e = int(np.searchsorted(offs, offs[k] + budget, side="right")) - 1
        e = min(n, max(e, k + 1))
        yield Texts(buf[offs[k] : offs[e]], offs[k : e + 1] - offs[k], k)
        k = e


def words(t: Texts, member: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(values, starts, ends, doc) of the maximal runs of member bytes within documents."""
    values = LOWER[t.data] if lower else t.data
    inside = np.zeros(len(values) + 2, dtype=bool)
    inside[1:-1] = member[values]
    edge = inside[1:] != inside[:-1]
    at = np.flatnonzero(edge)
    starts, ends = at[::2], at[1::2]
    # a run that crosses a document border is cut there
    cuts = t.offs[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(values))]
    cuts = np.unique(cuts)
    cuts = cuts[inside[cuts] & inside[cuts + 1]] if len(cuts) else cuts
    if len(cuts):
        starts, ends = np.sort(np.concatenate([starts, cuts])), np.sort(np.concatenate([ends, cuts]))
    doc = np.searchsorted(t.offs, starts, side="right") - 1
    return values, starts, ends, doc


def word_hashes(t: Texts, member: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, doc) of every word of the slice, in text order; a very long text goes in pieces."""
    hashes, docs = [], []
    for p in pieces(t, member) if len(t.data) > 8 * SLICE_BYTES else (t,):
        values, starts, ends, doc = words(p, member)
        hashes.append(span_hashes(values, starts, ends))
        docs.append(doc if p is t else doc + p.first)
    return np.concatenate(hashes), np.concatenate(docs)


def pieces(t: Texts, member: np.ndarray, budget: int = 4 * SLICE_BYTES) -> Iterator[Texts]:
    """Parts of single documents that end between words; ``first`` is the document's number."""
    for k in range(t.n):
        at, stop = int(t.offs[k]), int(t.offs[k + 1])
        while at < stop:
            end = min(stop, at + budget)
            while end < stop:  # on to the next byte that is in no word
                gap = np.flatnonzero(~member[LOWER[t.data[end : end + 4096]]])
                if len(gap):
                    end = min(stop, end + int(gap[0]))
                    break
                end += 4096
            end = min(end, stop)
            yield Texts(t.data[at:end], np.array([0, end - at]), k)
            at = end


def runs(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of every n consecutive entries; entry i covers i .. i+n-1."""
    m = len(h) - n + 1
    if m <= 0:
        return np.zeros(0, dtype=U64)
    out, mult = np.zeros(m, dtype=U64), 1
    for k in range(n):
        mult = (mult * 0xD1342543DE82EF95 + 1) & (2**64 - 1) | 1
        out += h[k : k + m] * U64(mult)
    return mix(out)


def doc_shingles(h: np.ndarray, doc: np.ndarray, n_docs: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (doc, hash of ``width`` consecutive words), sorted by both; a document with
    fewer words gives its whole sequence as one shingle, one without words none."""
    count = np.bincount(doc, minlength=n_docs)
    s = runs(h, width)
    own = doc[: len(s)]
    ok = own == doc[width - 1 :] if len(s) else np.zeros(0, bool)
    s, own = s[ok], own[ok]
    short = np.flatnonzero((count > 0) & (count < width))
    if len(short):
        first = np.concatenate([[0], np.cumsum(count)])
        extra = [mix(np.array([int(runs(h[first[d] : first[d + 1]], int(count[d]))[0]) ^ int(count[d])], dtype=U64))[0] for d in short]
        s, own = np.concatenate([s, np.array(extra, dtype=U64)]), np.concatenate([own, short])
    order = np.lexsort((s, own))
    s, own = s[order], own[order]
    keep = np.ones(len(s), dtype=bool)
    keep[1:] = (s[1:] != s[:-1]) | (own[1:] != own[:-1])
    return own[keep], s[keep]


# ------------------------------------------------------------- packed exchange


def record(dtype: list[tuple[str, str]], **cols: np.ndarray) -> np.ndarray:
    out = np.empty(len(next(iter(cols.values()))), dtype=dtype)
    for k, v in cols.items():
        out[k] = v
    return out


def pack(rows: np.ndarray) -> bytes:
    """A structured array column by column, which compresses far better than row by row."""
    return b"".join(np.ascontiguousarray(rows[k]).tobytes() for k in rows.dtype.names)


def unpack(blob: bytes, dtype: list[tuple[str, str]]) -> np.ndarray:
    d = np.dtype(dtype)
    n, at = len(blob) // d.itemsize, 0
    out = np.empty(n, dtype=d)
    for k in d.names:
        out[k] = np.frombuffer(blob, dtype=d[k], count=n, offset=at)
        at += n * d[k].itemsize
    return out


PACKED = "bucket int, rows binary"


Deal = str | Callable[[np.ndarray], np.ndarray]


def bucket_count(spark: SparkSession) -> int:
    """Buckets outnumber partitions by far, so that partitions stay even."""
    return max(1024, 8 * shuffle_width(spark))


def packed_batches(rows: np.ndarray, deal: Deal, buckets: int) -> Iterator[pa.RecordBatch]:
    """Deal structured rows into buckets by a hash column; one output row per bucket."""
    if not len(rows):
        return
    by = rows[deal].astype(U64) if isinstance(deal, str) else deal(rows)
    b = (mix(by) % U64(buckets)).astype(np.int32)
    order = np.argsort(b, kind="stable")
    rows, b = rows[order], b[order]
    at, stop = groups(b)
    yield pa.RecordBatch.from_arrays([pa.array(b[at], pa.int32()), pa.array([pack(rows[i:j]) for i, j in zip(at, stop, strict=True)], pa.binary())], names=["bucket", "rows"])


def exchange(df: DataFrame, produce: Callable[[Iterator[pa.RecordBatch]], Iterator[np.ndarray]], deal: Deal, dtype: list[tuple[str, str]], consume: Callable[[np.ndarray], Iterator[pa.RecordBatch]], schema: str, flush_rows: int = 1 << 18, combine: Callable[[np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """Shuffle structured rows by a hash column (or a function of the rows) in packed form.

    ``produce`` turns a partition into structured arrays.  They travel as one blob per map
    task and bucket, so the JVM moves few rows; ``combine`` may shrink what a task sends."""
    buckets = bucket_count(df.sparkSession)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        n = 0
        for part in produce(batches):
            for k in range(0, len(part), flush_rows):
                held.append(part[k : k + flush_rows])
                n += len(held[-1])
                if n >= flush_rows:
                    rows = np.concatenate(held)
                    held, n = [], 0
                    yield from packed_batches(combine(rows) if combine else rows, deal, buckets)
        if held:
            rows = np.concatenate(held)
            yield from packed_batches(combine(rows) if combine else rows, deal, buckets)

    return dealt(df.mapInArrow(resting(send), PACKED), dtype, consume, schema)


def dealt(packed: DataFrame, dtype: list[tuple[str, str]], consume: Callable[[np.ndarray], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """Bring the blobs of a bucket together.  A reducer sees one bucket at a time (sorted within
    its partition, which can spill), never the whole partition."""
    d = np.dtype(dtype)

    def receive(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_heap()
        now, held = None, []
        for batch in batches:
            for b, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if b != now and held:
                    rows = np.concatenate(held)
                    held = []
                    yield from consume(rows)
                now = b
                held.append(unpack(blob.as_buffer(), d))
        if held:
            rows = np.concatenate(held)
            held = []
            yield from consume(rows)

    return packed.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(resting(receive), schema)


def groups(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of equal keys in a sorted array."""
    if not len(keys):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return at, np.append(at[1:], len(keys))


def int_column(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and validity of an integer column."""
    valid = np.asarray(col.is_valid())
    return np.asarray(col.fill_null(0)).astype(np.int64), valid


# ------------------------------------------------------------- bounded bitmaps

_CHUNK = 32768


def hash_bitmap(df: DataFrame, column: str, max_bits: int = 1 << 27) -> tuple[np.ndarray, int]:
    """A bitmap over the long column's values and its number of bits.  Its size is bounded;
    beyond the bound it lets more values through, never fewer."""
    n = df.count()
    bits = 1 << 16
    while bits < min(max_bits, 64 * n):
        bits *= 2
    slot = F.pmod(F.col(column), F.lit(bits)) + 1  # the bitmap functions count positive values from 1
    got = df.groupBy(F.bitmap_bucket_number(slot).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(slot)).alias("m")).collect()
    out = np.zeros(bits // 8 + _CHUNK // 8, np.uint8)
    for r in got:  # at most max_bits / 32768 rows of 4 KB
        part = np.frombuffer(r["m"], np.uint8)
        at = (r["b"] - 1) * _CHUNK // 8
        out[at : at + len(part)] |= part
    return out, bits


def in_bitmap(values: np.ndarray, bitmap: np.ndarray, bits: int) -> np.ndarray:
    s = values.view(np.int64) % np.int64(bits)
    return (bitmap[s >> 3] >> (s & 7).astype(np.uint8)) & 1 == 1


def maybe_in(df: DataFrame, key: str, bitmap: np.ndarray, bits: int, outside: bool = False) -> DataFrame:
    """Rows whose key may be among the bitmap's values (or, with ``outside``, those whose key
    is not), before a join has to move their texts."""
    shared, at = df.sparkSession.sparkContext.broadcast(bitmap), df.columns.index(key)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(in_bitmap(int_column(batch.column(at))[0], shared.value, bits) ^ outside))

    return df.mapInArrow(resting(run), df.schema)


# ------------------------------------------------------------------ whole rows


def fresh_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` does not have in any case."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base += "_"
    return base


def row_keyed(docs: DataFrame) -> tuple[DataFrame, str]:
    """``docs`` with a column that identifies and orders its rows, and that column's name:
    doc_id itself, or a number in (doc_id, text) order where some are missing or repeated."""
    name = fresh_name(docs, "row_key")
    odd = docs.groupBy("doc_id").count().where((F.col("count") > 1) | F.col("doc_id").isNull()).limit(1).count()
    if not odd:
        return docs.withColumn(name, F.col("doc_id").cast("long")), name
    return persisted(docs.orderBy("doc_id", "text").withColumn(name, F.monotonically_increasing_id()), "ordered"), name
