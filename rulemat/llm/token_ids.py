"""Token ids and their binary output.

``Encoder`` gives the ids of whole texts exactly as the tokenizers library does for the
whole text.  Texts are cut at ASCII white space, every distinct word is encoded once per
worker (the vocabulary's pre-tokenizer never joins text across white space), and ids of a
slice are gathered with array operations.  Words are found by a hash and then compared byte
by byte, so no collision can give a word another word's ids.  Words of plain letters, digits and signs go
through the library's BPE model directly; any other word (apostrophes, special-token
strings, characters outside Latin) goes through the library's full chain.

The file format is a static range asymmetric numeral system: frequencies counted over the
whole corpus, scaled to 2**20, are shared by all blocks; a block of about a million ids is
dealt over interleaved lanes with 64-bit states and 32-bit renormalisation.  A block stores
its final states, checkpoints (states and word offset at a few steps, so that one block can
be decoded from several places at once), its words and a CRC-32 of its ids.

Defined cases: null text is empty (only the end id); rows are ordered by doc_id, nulls
first, rows that repeat a doc_id by text; an empty table gives no blocks and no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BYTE_MASK, NOT_SPACE, SLICE_BYTES, Texts, discard, int_column, persisted, pieces, resting, shared_dir, shuffle_width, slices, span_hashes, trim_heap, unaligned, words

U64 = np.uint64
SCALE_BITS = 20
LOW = 1 << 31
LANES = 4096
BLOCK_IDS = 1 << 20
CHECKPOINT_STEPS = 128
#: The id that ends every document.
END_ID = 1


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


# -------------------------------------------------------------------- encoding


def _kinds() -> np.ndarray:
    """By code point below 0x180: 1 letter, 2 digit, 3 sign; 0 where the full chain is needed."""
    import unicodedata

    kind = np.zeros(0x180, np.uint8)
    for c in range(0x21, 0x180):
        x = chr(c)
        cat = unicodedata.category(x)
        plain = unicodedata.normalize("NFC", x) == x and len(x.lower()) == 1 and not x.isspace() and cat[0] not in "ZC"
        kind[c] = plain * (1 if cat[0] == "L" else 2 if cat[0] == "N" else 3)
    kind[0x27] = 0  # contractions
    return kind


class Encoder:
    """Encodes slices of texts; keeps the ids of words it has seen, up to a bound."""

    MAX_WORDS = 1_500_000
    MAX_POOL = 1 << 25
    MAX_PIECES = 250_000
    #: The same for a lean encoder.
    LEAN_WORDS, LEAN_PIECES = 400_000, 80_000
    _own: dict[str, Encoder] = {}

    def __init__(self, path: str, lean: bool = False):
        import os

        self.max_words, self.max_pieces = (self.LEAN_WORDS, self.LEAN_PIECES) if lean else (self.MAX_WORDS, self.MAX_PIECES)

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.full = Tokenizer.from_file(path)
        self.bpe = Tokenizer(self.full.model)
        self.bpe.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        vocab = self.full.get_vocab(with_added_tokens=False)
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for w, i in vocab.items() if w.endswith("</w>")]] = True
        self.kinds = _kinds()
        visible = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
        hidden = iter(range(256, 512))
        self.alphabet = "".join(chr(b) if b in visible else chr(next(hidden)) for b in range(256))
        # only for a vocabulary whose chain is the one that the short cut reproduces
        self.direct = "'s|'t|'re|'ve|'m|'ll|'d|[\\\\p{L}]+|[\\\\p{N}]|[^\\\\s\\\\p{L}\\\\p{N}]+" in self.full.to_str()[:5_000]
        self.clear()

    @classmethod
    def of(cls, path: str) -> Encoder:
        if path not in cls._own:
            cls._own[path] = cls(path)
        return cls._own[path]

    @classmethod
    def lent(cls, path: str, lean: bool) -> Encoder:
        """The worker's encoder, or a lean one that ends with the task: Spark deals tasks over all
        workers that wait, so else each of them, not only those at work, comes to hold caches."""
        return cls(path, lean=True) if lean else cls.of(path)

    @classmethod
    def drop(cls) -> None:
        """Free what a worker that encoded keeps; the stages after encoding have no use for it."""
        if cls._own:
            cls._own.clear()
            trim_heap()

    def clear(self) -> None:
        self.pieces: dict[str, bytes] = {}  # ids of a piece as 32-bit integers
        self.keys = np.zeros(0, U64)  # sorted
        self.place = np.zeros(0, np.int32)  # of a known word's bytes in the pool, and their number
        self.size = np.zeros(0, np.int32)
        self.pool = np.zeros(8, np.uint8)  # ends in eight zeros
        self.at = np.zeros(0, np.int32)
        self.count = np.zeros(0, np.int32)
        self.ids = np.zeros(0, np.uint32)

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, np.uint32).tobytes() for e in self.full.encode_batch_fast(texts, add_special_tokens=False)]

    def _new_words(self, ws: list[bytes]) -> list[bytes]:
        texts = [w.decode() for w in ws]
        out: list[bytes | None] = [None] * len(texts)
        points = np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)
        lens = np.fromiter(map(len, texts), np.int64, len(texts))
        first = np.concatenate([[0], np.cumsum(lens)])
        kind = np.where(points < 0x180, self.kinds[np.minimum(points, 0x17F)], 0)
        own = np.repeat(np.arange(len(texts)), lens)
        plain = np.bincount(own[kind == 0], minlength=len(texts)) == 0
        if not self.direct:
            plain[:] = False
        # "<|" may begin a special token
        angle = np.flatnonzero((points[:-1] == 0x3C) & (points[1:] == 0x7C))
        plain[own[angle]] = False
        cut = np.zeros(len(points) + 1, bool)
        cut[first] = True
        cut[1:-1] |= (kind[1:] != kind[:-1]) | (kind[1:] == 2)
        bounds = np.flatnonzero(cut).tolist()
        joined = "".join(texts)
        owner = own[np.array(bounds[:-1], np.int64)].tolist() if len(points) else []
        pieces = [joined[a:b].lower() for a, b in zip(bounds, bounds[1:], strict=False)]
        if len(self.pieces) > self.max_pieces:
            self.pieces = {}
        fresh = list({p for p, o in zip(pieces, owner, strict=True) if p not in self.pieces and plain[o]})
        if fresh:
            mapped = " ".join([p if p.isascii() else p.encode().decode("latin1").translate(self.alphabet) for p in fresh])
            ids = np.array(self.bpe.encode_batch_fast([mapped], add_special_tokens=False)[0].ids, np.uint32)
            stops = (4 * (np.flatnonzero(self.ends[ids]) + 1)).tolist()
            assert len(stops) == len(fresh)
            ids = ids.tobytes()
            start = 0
            for p, e in zip(fresh, stops, strict=True):
                self.pieces[p] = ids[start:e]
                start = e
        for p, o in zip(pieces, owner, strict=True):
            if plain[o]:
                have = out[o]
                out[o] = self.pieces[p] if have is None else have + self.pieces[p]
        hard = [k for k in range(len(texts)) if out[k] is None]
        for k, ids in zip(hard, self._whole([texts[k] for k in hard]), strict=True):
            out[k] = ids
        return out

    def encode(self, t: Texts) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all documents one after another, number of ids of each document)."""
        if len(t.data) > 8 * SLICE_BYTES:  # a very long text, piece by piece
            parts = [(p.first, self._encode(p)[0]) for p in pieces(t, NOT_SPACE)]
            n = np.bincount([k for k, _ in parts], weights=[len(x) for _, x in parts], minlength=t.n).astype(np.int64)
            return np.concatenate([x for _, x in parts]), n
        return self._encode(t)

    def _learn(self, where: np.ndarray, keys: np.ndarray, ws: list[bytes]) -> None:
        """Put words in at their places among the sorted keys."""
        got = self._new_words(ws)
        n = np.fromiter(map(len, got), np.int64, len(got)) >> 2
        size = np.fromiter(map(len, ws), np.int64, len(ws))
        self.keys = np.insert(self.keys, where, keys)
        self.at, self.count = np.insert(self.at, where, len(self.ids) + np.cumsum(n) - n), np.insert(self.count, where, n)
        self.place, self.size = np.insert(self.place, where, len(self.pool) - 8 + np.cumsum(size) - size), np.insert(self.size, where, size)
        self.ids = np.concatenate([self.ids, np.frombuffer(b"".join(got), np.uint32)])
        self.pool = np.concatenate([self.pool[:-8], np.frombuffer(b"".join(ws) + bytes(8), np.uint8)])

    def _encode(self, t: Texts) -> tuple[np.ndarray, np.ndarray]:
        values, starts, ends, doc = words(t, NOT_SPACE, lower=False)
        if not len(starts):
            return np.zeros(0, np.uint32), np.zeros(t.n, np.int64)
        uniq, sample, back = np.unique(span_hashes(values, starts, ends), return_index=True, return_inverse=True)
        where = np.searchsorted(self.keys, uniq)
        known = np.zeros(len(uniq), bool)
        inside = where < len(self.keys)
        known[inside] = self.keys[where[inside]] == uniq[inside]
        if not known.all():
            if len(self.keys) > self.max_words or len(self.pool) > self.MAX_POOL or len(self.ids) > self.MAX_POOL:
                self.clear()
                known[:], where[:] = False, 0
            new = sample[~known]
            raw = values.tobytes()
            self._learn(where[~known], uniq[~known], [raw[a:b] for a, b in zip(starts[new].tolist(), ends[new].tolist(), strict=True)])
            where = np.searchsorted(self.keys, uniq)
        slot = where[back]
        if not self._same(values, starts, ends, slot):  # two words share a hash: take the plain way
            got = self._whole([t.bytes_of(k).decode() for k in range(t.n)])
            return np.frombuffer(b"".join(got), np.uint32), np.fromiter(map(len, got), np.int64, len(got)) >> 2
        n = self.count[slot].astype(np.int64)
        stop = np.cumsum(n)
        pick = np.repeat(self.at[slot] - (stop - n), n) + np.arange(int(stop[-1]))
        return self.ids[pick], np.bincount(doc, weights=n, minlength=t.n).astype(np.int64)

    def _same(self, values: np.ndarray, starts: np.ndarray, ends: np.ndarray, slot: np.ndarray) -> bool:
        """Whether every word's bytes are those of the known word that it is taken for."""
        n = ends - starts
        if (self.size[slot] != n).any():
            return False
        count = (n + 7) >> 3
        stop = np.cumsum(count)
        step = 8 * (np.arange(int(stop[-1])) - np.repeat(stop - count, count))
        bits = BYTE_MASK[np.minimum(np.repeat(n, count) - step, 8)]
        pool = np.ndarray((len(self.pool) - 7,), "<u8", self.pool, strides=(1,))
        return not (((unaligned(values)[np.repeat(starts, count) + step] ^ pool[np.repeat(self.place[slot], count) + step]) & bits) != 0).any()


# --------------------------------------------------------- asymmetric numerals


def scaled(counts: np.ndarray) -> np.ndarray:
    """Frequencies that sum to 2**SCALE_BITS, at least 1 for every id that occurs."""
    total, size = int(counts.sum()), 1 << SCALE_BITS
    seen = counts > 0
    if not total:
        return np.zeros(len(counts), np.int64)
    if int(seen.sum()) > size:
        raise ValueError("more distinct ids than the table has room for")
    freq = np.where(seen, np.maximum(1, counts.astype(np.float64) * size / total), 0).astype(np.int64)
    over = int(freq.sum()) - size
    order = np.argsort(-freq, kind="stable")
    k = 0
    while over > 0:  # take from the most frequent, which loses least
        i = order[k % int(seen.sum())]
        take = min(over, max(0, freq[i] // 8)) or (1 if freq[i] > 1 else 0)
        freq[i], over, k = freq[i] - take, over - take, k + 1
    freq[order[0]] -= over
    return freq


class Coder:
    """Encoder and decoder of blocks under one shared table."""

    def __init__(self, freq: np.ndarray):
        self.freq = freq.astype(U64)
        self.cum = np.concatenate([[0], np.cumsum(freq)[:-1]]).astype(U64)
        self.symbol = np.repeat(np.arange(len(freq)), freq).astype(np.uint16 if len(freq) <= 1 << 16 else np.uint32)

    def encode(self, ids: np.ndarray) -> dict[str, object]:
        n = len(ids)
        lanes = max(1, min(LANES, n))
        steps = -(-n // lanes) if n else 0
        x = np.full(lanes, LOW, U64)
        groups: list[np.ndarray] = []
        marks: list[tuple[int, int, bytes]] = []  # step, words left to read from the end, states
        written = 0
        f, c = self.freq[ids], self.cum[ids]
        for step in range(steps - 1, -1, -1):
            a = step * lanes
            b = min(n, a + lanes)
            fs, y = f[a:b], x[: b - a]
            full = y >= fs << U64(43)
            if full.any():
                w = y[full]
                groups.append(w.astype(np.uint32))
                written += len(w)
                y = np.where(full, y >> U64(32), y)
            q = y // fs
            x[: b - a] = (q << U64(SCALE_BITS)) + (y - q * fs) + c[a:b]
            if step and step % CHECKPOINT_STEPS == 0:
                marks.append((step, written, x.tobytes()))
        stream = np.concatenate(groups[::-1]) if groups else np.zeros(0, np.uint32)
        marks = [(s, written - w, state) for s, w, state in marks[::-1]]
        return {"n_ids": n, "lanes": lanes, "states": x.tobytes(), "words": stream.tobytes(), "mark_steps": [m[0] for m in marks], "mark_words": [m[1] for m in marks], "mark_states": b"".join(m[2] for m in marks), "crc": zlib.crc32(ids.astype("<u4").tobytes())}

    def decode_part(self, block: dict[str, object], part: int) -> np.ndarray:
        """Ids from checkpoint ``part`` (0: the start) up to the next one."""
        n, lanes = int(block["n_ids"]), int(block["lanes"])
        steps = -(-n // lanes) if n else 0
        begins, offsets = [0, *block["mark_steps"]], [0, *block["mark_words"]]
        first, last = begins[part], begins[part + 1] if part + 1 < len(begins) else steps
        states = block["states"] if part == 0 else block["mark_states"][(part - 1) * lanes * 8 : part * lanes * 8]
        x = np.frombuffer(states, U64).copy()
        stream = np.frombuffer(block["words"], np.uint32)
        at = offsets[part]
        out = np.empty(min(n, last * lanes) - first * lanes, self.symbol.dtype)
        mask, pos = U64((1 << SCALE_BITS) - 1), 0
        for step in range(first, last):
            k = min(n, (step + 1) * lanes) - step * lanes
            y = x[:k]
            slot = y & mask
            s = self.symbol[slot]
            out[pos : pos + k] = s
            pos += k
            y = self.freq[s] * (y >> U64(SCALE_BITS)) + slot - self.cum[s]
            low = np.flatnonzero(y < U64(LOW))
            if len(low):
                y[low] = (y[low] << U64(32)) | stream[at : at + len(low)]
                at += len(low)
            x[:k] = y
        if last == steps and not (x == U64(LOW)).all():
            raise ValueError("a block does not end in its initial state")
        return out

    def decode(self, block: dict[str, object]) -> np.ndarray:
        parts = [self.decode_part(block, k) for k in range(len(block["mark_steps"]) + 1)]
        ids = np.concatenate(parts).astype(np.uint32)
        if zlib.crc32(ids.astype("<u4").tobytes()) != block["crc"]:
            raise ValueError("a block fails its checksum")
        return ids


# --------------------------------------------------------------------- corpus

_STAGED = "part int, seq int, before long, n_ids long, doc_ids binary, null_ids binary, lens binary, ids binary"
_BLOCK = "part int, seq int, before long, n_ids long, lanes int, states binary, mark_steps array<int>, mark_words array<int>, mark_states binary, words binary, crc long, doc_ids binary, null_ids binary, lens binary"


_LOWEST = -(2**63)


class Ranges:
    """Ranges of doc_id of about equal numbers of rows.  A doc_id (or its lack) that fills
    several of them is split further by the digest that orders its rows."""

    def __init__(self, docs: DataFrame, parts: int):
        at = [k / parts for k in range(1, parts)]
        got = docs.agg(F.percentile_approx(F.coalesce("doc_id", F.lit(_LOWEST).cast("long")), at, 10_000).alias("q")).first()["q"] if at else None
        self.bounds, times = np.unique(np.array(got or [], np.int64), return_counts=True)
        self.times = np.append(times, 1)
        self.first = np.cumsum(self.times) - self.times
        self.count = int(self.times.sum())

    def of(self, key: np.ndarray, valid: np.ndarray, digest: np.ndarray) -> np.ndarray:
        key = np.where(valid, key, _LOWEST)
        at = np.searchsorted(self.bounds, key, side="left")
        same = np.append(self.bounds, 0)[at] == key
        same &= at < len(self.bounds)
        within = ((digest >> U64(32)) * self.times[at].astype(U64) >> U64(32)).astype(np.int64)
        return self.first[at] + np.where(same, within, 0)


def _width(path: str) -> type:
    """Type that holds every id of a vocabulary."""
    from tokenizers import Tokenizer

    return np.uint16 if Tokenizer.from_file(path).get_vocab_size() <= 1 << 16 else np.uint32


def stage_ids(docs: DataFrame, path: str, dtype: type, parts: int | None = None, lean: bool = False) -> DataFrame:
    """Encode all texts and lay the ids down in ascending doc_id order, packed by about a
    million ids.  Ranges of doc_id go to one task each; a task sends its ids compressed.
    ``lean``: smaller slices, and no cache outlives its task, for more CPU time."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    parts = parts or max(8, shuffle_width(spark))
    ranges = Ranges(docs, parts)
    slice_bytes, flush_ids = (2 * SLICE_BYTES, BLOCK_IDS) if lean else (8 * SLICE_BYTES, 4 * BLOCK_IDS)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, z = Encoder.lent(path, lean), zstandard.ZstdCompressor(level=1)
        held: list[tuple[np.ndarray, ...]] = []

        def flush() -> Iterator[pa.RecordBatch]:
            key, valid, digest, n = (np.concatenate([h[k] for h in held]) for k in range(4))
            ids = np.concatenate([h[4] for h in held])
            to = ranges.of(key, valid, digest)
            first = np.concatenate([[0], np.cumsum(n)])
            order = np.argsort(to, kind="stable")
            at = np.flatnonzero(np.concatenate([[True], to[order][1:] != to[order][:-1]]))
            rows = []
            for i, j in zip(at, np.append(at[1:], len(order)), strict=True):
                own = order[i:j]
                size = n[own]
                stop = np.cumsum(size)
                pick = np.repeat(first[own] - (stop - size), size) + np.arange(int(stop[-1]))
                rows.append((int(to[own[0]]), key[own].tobytes(), valid[own].tobytes(), digest[own].tobytes(), size.astype(np.int32).tobytes(), z.compress(ids[pick].tobytes())))
            cols = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["part", "k", "v", "d", "n", "ids"])

        total = 0
        for batch in batches:
            key, valid = int_column(batch.column(0))
            for t in slices(batch.column(1), slice_bytes):
                ids, n = enc.encode(t)
                full = np.empty(len(ids) + t.n, dtype)
                stop = np.cumsum(n + 1)
                is_end = np.zeros(len(full), bool)
                is_end[stop - 1] = True
                full[is_end], full[~is_end] = END_ID, ids
                digest = span_hashes(t.data, t.offs[:-1], t.offs[1:])  # orders rows that repeat a doc_id
                held.append((key[t.first : t.first + t.n], valid[t.first : t.first + t.n], digest, n + 1, full))
                total += len(full)
                if total >= flush_ids:
                    yield from flush()
                    held, total = [], 0
        if held:
            yield from flush()

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        Encoder.drop()
        z, zc = zstandard.ZstdDecompressor(), zstandard.ZstdCompressor(level=1)
        now, held = None, []

        def lay(part: int) -> Iterator[pa.RecordBatch]:
            key, valid, digest, n = (np.concatenate([np.frombuffer(h[k], d) for h in held]) for k, d in enumerate((np.int64, bool, U64, np.int32)))
            ids = np.concatenate([np.frombuffer(z.decompress(h[4]), dtype) for h in held])
            n = n.astype(np.int64)
            first = np.concatenate([[0], np.cumsum(n)])
            order = np.lexsort((digest, key, valid))
            before, k, seq = 0, 0, 0
            stops = np.cumsum(n[order])
            while k < len(order):
                e = max(k + 1, int(np.searchsorted(stops, before + BLOCK_IDS, side="right")))
                own = order[k:e]
                size = n[own]
                stop = np.cumsum(size)
                pick = np.repeat(first[own] - (stop - size), size) + np.arange(int(stop[-1]))
                yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "seq": pa.array([seq], pa.int32()), "before": [before], "n_ids": [int(stop[-1])], "doc_ids": [key[own].tobytes()], "null_ids": [(~valid[own]).tobytes()], "lens": [size.tobytes()], "ids": [zc.compress(ids[pick].tobytes())]})
                before, k, seq = before + int(stop[-1]), e, seq + 1

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if row[0] != now and held:
                    yield from lay(now)
                    held = []
                now = row[0]
                held.append(row[1:])
        if held:
            yield from lay(now)

    sent = docs.mapInArrow(resting(send), "part int, k binary, v binary, d binary, n binary, ids binary")
    return sent.repartitionById(ranges.count, "part").sortWithinPartitions("part").mapInArrow(resting(settle), _STAGED)


def write_ids(docs: DataFrame, out_dir: str, path: str | None = None, lean: bool = False) -> DataFrame:
    """Write the corpus in the block format below ``out_dir`` (``blocks`` and ``table``)."""
    spark = docs.sparkSession
    path = path or vocabulary()
    dtype = _width(path)
    staged = persisted(stage_ids(docs, path, dtype, lean=lean), "token-ids")

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        Encoder.drop()
        z, counts = zstandard.ZstdDecompressor(), np.zeros(0, np.int64)
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                c = np.bincount(np.frombuffer(z.decompress(blob), dtype))
                if len(c) > len(counts):
                    counts, c = c, counts
                counts[: len(c)] += c
        seen = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int64()), pa.array(counts[seen], pa.int64())], names=["id", "n"])

    # one row per id of the vocabulary: its size bounds what comes to the driver
    got = staged.select("ids").mapInArrow(resting(tally), "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros(int(got["id"].max()) + 1 if len(got) else 1, np.int64)
    counts[got["id"].to_numpy(np.int64)] = got["n"].to_numpy(np.int64)
    freq = scaled(counts)
    seen = np.flatnonzero(freq)
    spark.createDataFrame([(int(i), int(freq[i])) for i in seen], "id long, freq long").coalesce(1).write.parquet(f"{out_dir}/table")

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        Encoder.drop()
        coder, z = Coder(freq), zstandard.ZstdDecompressor()
        kinds = {"part": pa.int32(), "seq": pa.int32(), "lanes": pa.int32(), "mark_steps": pa.list_(pa.int32()), "mark_words": pa.list_(pa.int32())}
        for batch in batches:
            for row in batch.to_pylist():
                block = coder.encode(np.frombuffer(z.decompress(row.pop("ids")), dtype))
                row |= block
                yield pa.RecordBatch.from_arrays([pa.array([row[c.split()[0]]], kinds.get(c.split()[0])) for c in _BLOCK.split(", ")], names=[c.split()[0] for c in _BLOCK.split(", ")])

    staged.mapInArrow(resting(code), _BLOCK).write.option("compression", "uncompressed").parquet(f"{out_dir}/blocks")
    discard(staged)
    return spark.read.schema(_BLOCK).parquet(f"{out_dir}/blocks")


def read_ids(spark: SparkSession, out_dir: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of every document, from the files."""
    blocks = spark.read.schema(_BLOCK).parquet(f"{out_dir}/blocks")
    got = spark.read.schema("id long, freq long").parquet(f"{out_dir}/table").toPandas()
    freq = np.zeros(int(got["id"].max()) + 1 if len(got) else 1, np.int64)
    freq[got["id"].to_numpy(np.int64)] = got["freq"].to_numpy(np.int64)
    # as many rows as the writer had ranges
    totals = {r["part"]: r["n"] for r in blocks.groupBy("part").agg(F.sum("n_ids").alias("n")).collect()}
    base, run = {}, 0
    for p in sorted(totals):
        base[p], run = run, run + totals[p]
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        Encoder.drop()
        coder = Coder(freq)
        for batch in batches:
            for row in batch.to_pylist():
                ids = coder.decode(row).astype("<u4")
                lens = np.frombuffer(row["lens"], np.int64)
                stop = np.cumsum(lens)
                raw = memoryview(ids.tobytes())
                cuts = [raw[4 * int(e - n) : 4 * int(e)] for e, n in zip(stop, lens, strict=True)]
                cols = [pa.array(np.frombuffer(row["doc_ids"], np.int64), mask=np.frombuffer(row["null_ids"], bool)), pa.array(base[row["part"]] + row["before"] + stop - lens), pa.array(lens), pa.array([zlib.crc32(c) for c in cuts], pa.int64())]
                yield pa.RecordBatch.from_arrays([*cols, *[pa.array([bytes(c) for c in cuts], pa.binary())] * with_ids], names=[c.split()[0] for c in schema.split(", ")])

    return blocks.mapInArrow(resting(decode), schema)


def token_ids(docs: DataFrame, path: str | None = None, lean: bool = False) -> DataFrame:
    """Write the ids of ``docs`` to the shared folder and read every document back."""
    out_dir = shared_dir(docs.sparkSession, "ids")
    write_ids(docs, out_dir, path, lean)
    return read_ids(docs.sparkSession, out_dir)


