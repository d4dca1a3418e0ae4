"""N-gram Jaccard join by grouped prefixes.

A document is its set of distinct word n-grams; two documents link when their sets' Jaccard
similarity reaches a threshold given in percent.

Grams are ordered from rare to frequent: a bounded list of the most frequent ones comes last in
the order of its counts, all others before it by hash.  The counts cover all documents, but for
grams that a task meets only once in a million; any common order gives the same links.  Two sets that link share a gram of their prefixes, so:

1. Documents with the same set collapse into one set, sets with the same prefix and size
   into one group.  A set also carries a 512-bit parity sketch: the number of differing bits
   of two sketches never exceeds the size of the sets' symmetric difference.
2. Prefix grams of groups are dealt out; grams of one group drop out.
3. Group pairs are filtered by size, by position in the prefix and by sketch, expanded to
   their members, filtered again, and verified on the whole sets.  A group stands there with
   the sketch of its head and the most bits in which a member's sketch differs from it: two
   members differ by at least the heads' difference less both of these, whoever they are.
4. First every posting list and every group is compared with one member in its middle.  What
   links is joined to components, and afterwards only pairs of sets in different components
   are compared, all of them.  So no link between different components is lost, while groups
   of thousands of near copies need no quadratic number of verifications.

Result: one row per document with its component (smallest doc_id that links reach).

Defined cases: null or empty text, or text without words, has an empty set and links with
nothing; fewer words than n make one gram of the whole sequence; rows that repeat or lack a
doc_id are documents of their own, ordered as in ``keyed_documents``; a component without
doc_ids has a null id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graphops import components
from .common import NOT_SPACE, Texts, doc_shingles, exchange, groups, hash_bitmap, in_bitmap, int_column, keyed_documents, mix, persisted, record, resting, slices, word_hashes

U64 = np.uint64
#: Most entries of the list of frequent grams.
MAX_FREQUENT = 200_000
LEAST_FREQUENT = 8
#: Members that one task verifies against their leader.
MEMBERS = 512
#: Rows of a posting list that are compared with each other at once.
BLOCK = 2048
_SKETCH = 8  # longs
_B = [f"b{k}" for k in range(_SKETCH)]


def shingles(t: Texts, width: int) -> tuple[np.ndarray, np.ndarray]:
    h, doc = word_hashes(t, NOT_SPACE)
    return doc_shingles(h, doc, t.n, width)


def prefix_size(n: np.ndarray, percent: int) -> np.ndarray:
    return n - (percent * n + 99) // 100 + 1


def least_overlap(a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
    """Smallest intersection of linked sets of sizes a and b."""
    return (percent * (a + b) + 99 + percent) // (100 + percent)


def frequent_grams(keyed: DataFrame, width: int) -> np.ndarray:
    """The most frequent grams, from less to more frequent; at most MAX_FREQUENT of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        n = 0

        def flush() -> pa.RecordBatch:
            x = np.sort(np.concatenate(held))
            a, b = groups(x)
            some = b - a > 1
            return pa.RecordBatch.from_arrays([pa.array(x[a[some]].view(np.int64)), pa.array(b[some] - a[some])], names=["gram", "n"])

        for batch in batches:
            for t in slices(batch.column(0)):
                held.append(shingles(t, width)[1])
                n += len(held[-1])
                if n > 1 << 20:
                    yield flush()
                    held, n = [], 0
        if held:
            yield flush()

    counted = keyed.select("text").mapInArrow(resting(run), "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")).where(F.col("n") >= LEAST_FREQUENT)
    # bounded by MAX_FREQUENT rows of two longs
    top = counted.orderBy(F.desc("n"), "gram").limit(MAX_FREQUENT).toArrow()
    return np.asarray(top["gram"]).view(U64)[::-1].copy()


def _sets(keyed: DataFrame, width: int, percent: int, frequent: np.ndarray) -> DataFrame:
    """Every document's set in short: size, digests, prefix and sketch."""
    spark = keyed.sparkSession
    by_hash = np.argsort(frequent, kind="stable")
    shared = spark.sparkContext.broadcast((frequent[by_hash], (by_hash + 1).astype(np.int32)))
    schema = "key long, n long, s1 long, s2 long, g long, prefix binary, " + ", ".join(f"{b} long" for b in _B)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, ranks = shared.value
        for batch in batches:
            keys, _ = int_column(batch.column(0))
            for t in slices(batch.column(1)):
                own, h = shingles(t, width)
                n = np.bincount(own, minlength=t.n)
                first = np.concatenate([[0], np.cumsum(n)])
                rank = np.zeros(len(h), np.int32)
                if len(known):
                    at = np.minimum(np.searchsorted(known, h), len(known) - 1)
                    rank = np.where(known[at] == h, ranks[at], 0)
                hot = np.flatnonzero(rank)
                order = np.arange(len(h))
                if len(hot):  # hashes are sorted within documents already: frequent ones move to the end
                    order = np.lexsort((h, rank, own))
                size = np.where(n > 0, prefix_size(n, percent), 0)
                raw = h[order]
                prefix = [raw[a:b].tobytes() for a, b in zip(first[:-1].tolist(), (first[:-1] + size).tolist(), strict=True)]
                full = n > 0
                total = lambda x: np.diff(np.concatenate([np.zeros(1, U64), np.cumsum(x, dtype=U64)])[first])  # noqa: E731, B023
                s1, s2 = mix(total(mix(h.copy())) + n.astype(U64)), mix(total(mix(h ^ U64(0xA5A5A5A5A5A5A5A5))) ^ n.astype(U64))
                stop = np.concatenate([[0], np.cumsum(size)])
                where = np.repeat(first[:-1] - stop[:-1], size) + np.arange(int(stop[-1]))
                place = np.arange(int(stop[-1])) - np.repeat(stop[:-1], size)
                tagged = mix(raw[where] + place.astype(U64) * U64(0x9E3779B97F4A7C15))
                g = mix(np.diff(np.concatenate([np.zeros(1, U64), np.cumsum(tagged, dtype=U64)])[stop]) ^ n.astype(U64))
                bit = (mix(h ^ U64(0x5851F42D4C957F2D)) >> U64(55)).astype(np.int64)
                sketch = np.packbits(np.bincount(own * 512 + bit, minlength=t.n * 512).astype(np.uint8) & 1).reshape(t.n, 64).view(np.int64)
                k = np.flatnonzero(full)
                cols = [keys[t.first : t.first + t.n][k], n[k], s1[k].view(np.int64), s2[k].view(np.int64), g[k].view(np.int64)]
                yield pa.RecordBatch.from_arrays([*map(pa.array, cols), pa.array([prefix[i] for i in k], pa.binary()), *(pa.array(np.ascontiguousarray(sketch[k, i])) for i in range(_SKETCH))], names=[c.split()[0] for c in schema.split(", ")])

    return keyed.select("key", "text").mapInArrow(resting(run), schema)


_POST = [("gram", "u8"), ("gid", "i8"), ("n", "u4"), ("pos", "u4")]


def postings(grouped: DataFrame) -> DataFrame:
    """(gram, gid, n, pos) of prefix grams that at least two groups share."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            gid, n = int_column(batch.column(0))[0], int_column(batch.column(1))[0]
            blobs = batch.column(2).to_pylist()
            size = np.fromiter((len(b) // 8 for b in blobs), np.int64, len(blobs))
            pos = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
            yield record(_POST, gram=np.frombuffer(b"".join(blobs), U64), gid=np.repeat(gid, size), n=np.repeat(n, size), pos=pos)

    def keep(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        x = x[np.argsort(x["gram"], kind="stable")]
        a, b = groups(x["gram"])
        x = x[np.repeat(b - a > 1, b - a)]
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x["gram"]).view(np.int64)), pa.array(np.ascontiguousarray(x["gid"])), pa.array(x["n"].astype(np.int64)), pa.array(x["pos"].astype(np.int64))], names=["gram", "gid", "n", "pos"])

    return exchange(grouped.select("gid", "n", "prefix"), send, "gram", _POST, keep, "gram long, gid long, n long, pos long")


_CAND = [("gram", "u8"), ("gid", "i8"), ("n", "u4"), ("pos", "u4"), ("comp", "i8"), ("far", "u4"), ("bits", f"({_SKETCH},)u8")]


def _differ(bits: np.ndarray, other: np.ndarray) -> np.ndarray:
    return np.bitwise_count(bits ^ other).sum(axis=-1, dtype=np.int64)


def _pairs(rows: DataFrame, percent: int, middle_only: bool) -> DataFrame:
    """Candidate group pairs (a, b) of posting rows (gram, gid, n, pos, comp, far, sketch).

    ``far`` is how many bits of a sketch may differ in the rows that the posting row stands for.

    With ``middle_only`` each list's rows are compared with the row whose sketch is nearest
    to the list's majority; otherwise all rows of different components with each other.
    """

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            cols = [int_column(batch.column(k))[0] for k in range(6 + _SKETCH)]
            out = np.empty(len(cols[0]), dtype=_CAND)
            for name, c in zip(("gram", "gid", "n", "pos", "comp", "far"), cols, strict=False):
                out[name] = c.view(U64) if name == "gram" else c
            out["bits"] = np.stack([c.view(U64) for c in cols[6:]], axis=1)
            yield out

    def fit(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        a, b = x["n"].astype(np.int64), y["n"].astype(np.int64)
        need = least_overlap(a, b, percent)
        ahead = 1 + np.minimum(a - x["pos"] - 1, b - y["pos"] - 1)
        ok = (np.minimum(a, b) >= need) & (ahead >= need) & (x["gid"] != y["gid"])
        k = np.flatnonzero(ok)
        if len(k):
            x, y = x[k] if len(x) == len(ok) else x, y[k] if len(y) == len(ok) else y
            a, b = x["n"].astype(np.int64), y["n"].astype(np.int64)
            apart = np.maximum(_differ(x["bits"], y["bits"]) - x["far"].astype(np.int64) - y["far"].astype(np.int64), 0)
            ok[k] = (a + b - apart) // 2 >= least_overlap(a, b, percent)
        return ok

    def settle(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        x = x[np.argsort(x["gram"], kind="stable")]
        left: list[np.ndarray] = []
        right: list[np.ndarray] = []
        size = 0

        def emit() -> pa.RecordBatch:
            a, b = np.concatenate(left), np.concatenate(right)
            a, b = np.minimum(a, b), np.maximum(a, b)
            order = np.lexsort((b, a))
            a, b = a[order], b[order]
            new = np.ones(len(a), bool)
            new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
            return pa.RecordBatch.from_arrays([pa.array(a[new]), pa.array(b[new])], names=["a", "b"])

        for i, j in zip(*groups(x["gram"]), strict=True):
            r = x[i:j]
            if middle_only:
                if len(r) > 2:
                    flat = np.unpackbits(np.ascontiguousarray(r["bits"]).view(np.uint8), axis=1)
                    major = np.packbits(flat.sum(axis=0, dtype=np.int64) * 2 > len(r)).view(U64)
                    m = int(np.argmin(_differ(r["bits"], major)))
                else:
                    m = 0
                ok = fit(r, r[m : m + 1])
                if ok.any():
                    left.append(r["gid"][ok])
                    right.append(np.full(int(ok.sum()), r["gid"][m]))
                    size += int(ok.sum())
            elif (r["comp"] != r["comp"][0]).any():
                r = r[np.lexsort((r["gid"], r["n"]))]
                # sizes bound how far ahead a partner can be
                reach = np.searchsorted(r["n"], r["n"].astype(np.int64) * 100 // percent, side="right")
                for s in range(0, len(r), BLOCK):
                    e = min(len(r), s + BLOCK)
                    for k in range(s, e):
                        y = r[k + 1 : reach[k]]
                        y = y[y["comp"] != r["comp"][k]]
                        if len(y):
                            ok = fit(y, r[k : k + 1])
                            if ok.any():
                                left.append(y["gid"][ok])
                                right.append(np.full(int(ok.sum()), r["gid"][k]))
                                size += int(ok.sum())
                    if size > 1 << 18:
                        yield emit()
                        left, right, size = [], [], 0
            if size > 1 << 18:
                yield emit()
                left, right, size = [], [], 0
        if size:
            yield emit()

    return exchange(rows.select("gram", "gid", "n", "pos", "comp", "far", *_B), send, "gram", _CAND, settle, "a long, b long", flush_rows=1 << 17).distinct()


def verify(keyed: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) of set keys that link.  Sets are made again from the texts concerned,
    and each pair's leader is compared with its members in portions."""
    spark = keyed.sparkSession
    counts = pairs.groupBy("b").agg(F.count("*").alias("members"))
    leads = counts.select(F.col("b").alias("lead"), (F.floor((F.col("members") - 1) / MEMBERS) + 1).alias("portions"))
    sent = pairs.select(F.col("b").alias("lead"), F.col("a").alias("key")).join(leads, "lead").select("lead", F.pmod(F.xxhash64("key"), F.col("portions")).alias("portion"), "key")
    own = leads.select("lead", F.explode(F.sequence(F.lit(0).cast("long"), F.col("portions") - 1)).alias("portion"), F.col("lead").alias("key"))
    needs = persisted(sent.unionByName(own), "verify")
    bitmap, bits = hash_bitmap(needs.select("key").distinct(), "key")
    shared = spark.sparkContext.broadcast(bitmap)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, _ = int_column(batch.column(0))
            k = np.flatnonzero(in_bitmap(keys, shared.value, bits))
            texts = batch.column(1).take(pa.array(k))
            for t in slices(texts):
                doc, h = shingles(t, width)
                at = np.searchsorted(doc, np.arange(t.n + 1))
                yield pa.RecordBatch.from_arrays([pa.array(keys[k[t.first : t.first + t.n]]), pa.array([h[a:b].tobytes() for a, b in zip(at, at[1:], strict=False)], pa.binary())], names=["key", "grams"])

    sets = keyed.select("key", "text").mapInArrow(resting(make), "key long, grams binary")
    rows = needs.join(sets, "key").select("lead", "portion", "key", "grams").withColumn("member", F.col("key") != F.col("lead"))
    rows = rows.repartition("lead", "portion").sortWithinPartitions("lead", "portion", "member")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lead, mine = None, np.zeros(0, U64)
        for batch in batches:
            a, b = [], []
            for who, _, key, grams, member in zip(*(c.to_pylist() if i != 3 else c for i, c in enumerate(batch.columns)), strict=True):
                h = np.frombuffer(grams.as_buffer(), U64)
                if not member:
                    lead, mine = who, h.copy()
                elif who == lead and len(h) and len(mine):
                    at = np.minimum(np.searchsorted(mine, h), len(mine) - 1)
                    both = int((mine[at] == h).sum())
                    if 100 * both >= percent * (len(mine) + len(h) - both):
                        a.append(key)
                        b.append(who)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return rows.mapInArrow(resting(compare), "a long, b long")


def jaccard_components(docs: DataFrame, width: int = 4, percent: int = 85) -> DataFrame:
    """(key, doc_id, n_shingles, component_id) of every document."""
    keyed = keyed_documents(docs)
    frequent = frequent_grams(keyed, width)
    full = persisted(_sets(keyed, width, percent, frequent), "sets")
    # documents with one set, sets with one prefix and size
    sets = full.groupBy("s1", "s2").agg(F.min("key").alias("key"), F.first("n").alias("n"), F.first("g").alias("g"), *[F.first(b).alias(b) for b in _B])
    prefixes = full.groupBy("g", "n").agg(F.min("key").alias("gid"), F.first("prefix").alias("prefix"), F.min_by(F.struct(*_B), "key").alias("head"))
    prefixes = persisted(prefixes, "groups")
    from_head = sum((F.bit_count(F.col(b).bitwiseXOR(F.col(f"head.{b}"))) for b in _B), F.lit(0))
    members = persisted(sets.join(prefixes.select("g", "n", "gid", "head"), ["g", "n"]).select("key", "gid", "n", "s1", "s2", *_B, from_head.alias("from_head")), "members")
    post = persisted(postings(prefixes), "postings")
    heads = prefixes.select("gid", "head.*")

    def expand(group_pairs: DataFrame, comp: DataFrame | None) -> DataFrame:
        m = members.select("key", "gid", "n", *_B)
        m = m.withColumn("comp", F.col("key")) if comp is None else m.join(comp, F.col("key") == F.col("node"), "left").withColumn("comp", F.coalesce("component", "key")).drop("node", "component")
        x, y = (m.select(*[F.col(c).alias(f"{p}_{c}") for c in m.columns]) for p in "xy")
        differ = sum((F.bit_count(F.col(f"x_{b}").bitwiseXOR(F.col(f"y_{b}"))) for b in _B), F.lit(0))
        need = F.floor((percent * (F.col("x_n") + F.col("y_n")) + 99 + percent) / (100 + percent))
        out = group_pairs.join(x, F.col("a") == F.col("x_gid")).join(y, F.col("b") == F.col("y_gid"))
        out = out.where((F.col("x_comp") != F.col("y_comp")) & ((F.col("a") != F.col("b")) | (F.col("x_key") < F.col("y_key"))) & (F.floor((F.col("x_n") + F.col("y_n") - differ) / 2) >= need))
        return out.select(F.col("x_key").alias("a"), F.col("y_key").alias("b"))

    # first round: the middle of each posting list, the head of each group
    first = _pairs(post.join(heads, "gid").withColumn("comp", F.col("gid")).withColumn("far", F.lit(0).cast("long")), percent, True)
    inside = members.where(F.col("key") != F.col("gid")).select(F.col("key").alias("a"), F.col("gid").alias("b"))
    links = persisted(verify(keyed, persisted(first.unionByName(inside), "pairs"), width, percent), "links")
    comp = persisted(components(links, persisted), "components")
    # second round: whatever is still apart.  A group in several components differs from all
    state = members.select("key", "gid", "from_head").join(comp, F.col("key") == F.col("node"), "left").groupBy("gid").agg(F.min(F.coalesce("component", "key")).alias("low"), F.max(F.coalesce("component", "key")).alias("high"), F.max("from_head").cast("long").alias("far"))
    state = persisted(state.select("gid", F.when(F.col("low") == F.col("high"), F.col("low")).otherwise(-1 - F.col("gid")).alias("comp"), (F.col("low") != F.col("high")).alias("mixed"), "far"), "group-state")
    apart = _pairs(post.join(heads, "gid").join(state.select("gid", "comp", "far"), "gid"), percent, False)
    own = state.where("mixed").select(F.col("gid").alias("a"), F.col("gid").alias("b"))
    more = persisted(expand(apart.unionByName(own), comp), "pairs")
    links = links.unionByName(persisted(verify(keyed, more, width, percent), "links"))
    comp = components(links, persisted)
    member_of = members.select("s1", "s2", F.col("key").alias("set_key")).join(comp, F.col("set_key") == F.col("node"), "left").select("s1", "s2", F.coalesce("component", "set_key").alias("component"))
    placed = full.select("key", "n", "s1", "s2").join(member_of, ["s1", "s2"]).select("key", "n", "component")
    out = keyed.select("key", "doc_id").join(placed, "key", "left").select("key", "doc_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_shingles"), F.coalesce("component", "key").alias("component"))
    return out


def component_ids(joined: DataFrame) -> DataFrame:
    """Name components by doc_id: keys are doc_ids unless some are missing or repeated."""
    if joined.where(~F.col("key").eqNullSafe(F.col("doc_id"))).limit(1).isEmpty():
        return joined.withColumn("component_id", F.col("component"))
    names = joined.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    return joined.join(names, "component")


def join_digests(docs: DataFrame, width: int = 4, percent: int = 85) -> DataFrame:
    return component_ids(persisted(jaccard_components(docs, width, percent), "joined")).select("doc_id", "n_shingles", "component_id")


