"""Toxicity by weak supervision.

Voters are lexicons and patterns: insults of a fixed list, word beginnings mined from labelled
training rows, and shapes of the text (capitals, exclamation, symbols).

1. Lexicon.  Word beginnings are counted in all labelled training rows; those that stand out in
   toxic ones become voters (at most ``MAX_VOTERS``) and features of the classifier (at most
   ``MAX_FEATURES``).
2. Label model.  Every training text, labelled or not, gives the set of voters that fire in it.
   Expectation maximisation over these vote patterns estimates how often each voter fires in
   toxic and in clean texts, and from what remains correlated given the class it discounts
   voters that repeat each other.  Labels only give the rates that it starts from, which weigh
   as much as ``ANCHOR`` texts; a posterior rests on votes alone.
3. Classifier.  A linear model over word beginnings learns the posteriors, not the labels, of at
   most ``MAX_LABELLED`` labelled training rows per class (the smallest hashes of doc_id), and
   scores every whole text.

Only labels of rows outside the held-out quarter (crc32 of doc_id modulo 4 is 2) are read, and
no score sees labels, lang, source or doc_id.

Defined cases: null and empty texts get a score like any other; rows with null label are not
labelled; a doc_id labelled several times counts as toxic if any label says so; without
labelled rows of both classes the fixed list alone makes the score; every row is scored on its
own; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ALNUM, BYTE_MASK, SLICE_BYTES, Texts, discard, fresh_name, groups, int_column, mix, persisted, pieces, resting, shuffle_width, slices, span_hashes, unaligned, words

U64 = np.uint64
MAX_LABELLED = 2500
THRESHOLD = 0.3
MAX_VOTERS = 192
MAX_FEATURES = 4096
#: Most word beginnings of toxic rows that are counted in clean ones, the most frequent first.
MAX_CANDIDATES = 1 << 18
#: Least chi-square of presence against label, and least ratio of the shares of toxic and clean
#: rows, of a voter and of a feature.
VOTER, FEATURE = (25, 20), (15, 6)
#: Training texts whose weight the rates known from labels have in the label model.
ANCHOR = 50
ROUNDS = 12
#: Labels that are handed to the tasks as arrays; beyond, they are joined.
MAX_SHARED_LABELS = 1 << 21
#: Lengths in bytes of the word beginnings that are features; 0 is the whole word.
BEGINNINGS = (0, 4, 5, 6)
# Common insults.
INSULTS = ("idiot", "moron", "stupid", "loser", "scum", "trash", "pathetic", "worthless", "disgusting", "clown")


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


# -------------------------------------------------------------------- features


def _hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> list[np.ndarray]:
    """Hashes of whole words and word beginnings; words shorter than a beginning have none."""
    eight = unaligned(values)[starts]
    return [span_hashes(values, starts, ends) if n == 0 else mix((eight & BYTE_MASK[n]) + U64(n * 0x9E3779B97F4A7C15 % 2**64)) for n in BEGINNINGS]


def shapes(t: Texts) -> np.ndarray:
    """Pattern voters: shares of capitals, exclamation marks and symbols, per document."""
    size = np.maximum(1, np.diff(t.offs))
    total = lambda flags: np.diff(np.concatenate([[0], np.cumsum(flags)])[t.offs])
    d = t.data
    upper = total((d >= 65) & (d <= 90)) / size > 0.3
    shout = total(d == 33) / size > 0.02
    symbols = total((d == 35) | (d == 36) | (d == 37) | (d == 38) | (d == 42)) / size > 0.05
    return np.stack([upper, shout, symbols], axis=1)


SHAPES = 3


def _distinct(own: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((h, own))
    own, h = own[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (own[1:] != own[:-1])
    return own[new], h[new]


def features(t: Texts, keys: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (document, feature hash) pairs of a slice, or (document, place among ``keys``)
    of those in a sorted list.  A very long text goes piece by piece."""
    if keys is not None:
        door = np.zeros(1 << 16, bool)
        door[(keys >> U64(48)).astype(np.int64)] = True
    own, found = [np.zeros(0, np.int64)], [np.zeros(0, U64 if keys is None else np.int64)]
    whole = len(t.data) <= 8 * SLICE_BYTES
    for p in (t,) if whole else pieces(t, ALNUM):
        values, starts, ends, doc = words(p, ALNUM)
        parts = [found[0]]
        of = [own[0]]
        for n, h in zip(BEGINNINGS, _hashes(values, starts, ends), strict=True):
            ok = ends - starts >= max(n, 3)
            if keys is not None and len(keys):
                k = np.flatnonzero(ok & door[(h >> U64(48)).astype(np.int64)])
                at = np.minimum(np.searchsorted(keys, h[k]), len(keys) - 1)
                hit = keys[at] == h[k]
                k, h = k[hit], at[hit]
                of.append(doc[k])
                parts.append(h)
            elif keys is None:
                of.append(doc[ok])
                parts.append(h[ok])
        a, b = _distinct(np.concatenate(of) + (0 if p is t else p.first), np.concatenate(parts))
        own.append(a)
        found.append(b)
    own, found = np.concatenate(own), np.concatenate(found)
    return (own, found) if whole else _distinct(own, found)


def insult_hashes() -> np.ndarray:
    text = "".join(INSULTS).encode()
    ends = np.cumsum([len(w) for w in INSULTS])
    starts = ends - [len(w) for w in INSULTS]
    return _hashes(np.frombuffer(text, np.uint8), starts, ends)[0]


# --------------------------------------------------------------- labelled rows


def labelled(docs: DataFrame, known: DataFrame) -> DataFrame:
    """(doc_id, y, text) of the labelled rows.  Few labels travel to the texts as two arrays
    (18 MB at most); more are joined."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if known.count() > MAX_SHARED_LABELS:
        return docs.join(known, "doc_id").select("doc_id", "y", "text")
    got = known.orderBy("doc_id").toArrow()
    shared = docs.sparkSession.sparkContext.broadcast((np.asarray(got["doc_id"]), np.asarray(got["y"]).astype(np.int8)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, y = shared.value
        for batch in batches:
            key, valid = int_column(batch.column(0))
            at = np.minimum(np.searchsorted(ids, key), max(0, len(ids) - 1))
            k = np.flatnonzero(valid & (ids[at] == key)) if len(ids) else np.zeros(0, np.int64)
            pick = pa.array(k)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pick), pa.array(y[at[k]].astype(np.int32)), batch.column(1).take(pick)], names=["doc_id", "y", "text"])

    return docs.mapInArrow(resting(run), "doc_id long, y int, text string")


def _counts(rows: DataFrame, keys: np.ndarray | None = None) -> DataFrame:
    """(h, n): in how many rows each feature (of a list, or any) occurs."""
    shared = rows.sparkSession.sparkContext.broadcast(keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted, held, n = shared.value, [], 0

        def flush() -> pa.RecordBatch:
            x = np.sort(np.concatenate(held))
            a, b = groups(x)
            return pa.RecordBatch.from_arrays([pa.array(x[a].view(np.int64)), pa.array(b - a)], names=["h", "n"])

        for batch in batches:
            for t in slices(batch.column(0)):
                h = features(t, wanted)[1]
                held.append(h if wanted is None else wanted[h])
                n += len(h)
                if n > 1 << 20:
                    yield flush()
                    held, n = [], 0
        if n:
            yield flush()

    return rows.select("text").mapInArrow(resting(run), "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))


@dataclass
class Lexicon:
    """Word beginnings that occur in toxic rows, with the labelled rows they occur in."""

    keys: np.ndarray  # sorted
    pos: np.ndarray
    neg: np.ndarray
    n_pos: int
    n_neg: int

    def standing_out(self, chi: float, rate: float, most: int) -> np.ndarray:
        """Places of the keys that mark toxic rows, the strongest first."""
        all_, n = self.pos + self.neg, self.n_pos + self.n_neg
        expect = all_ * self.n_pos / n
        signed = (self.pos - expect) ** 2 / np.maximum(1e-9, expect * (1 - self.n_pos / n)) * np.sign(self.pos - expect)
        ratio = (self.pos + 0.1) / (self.n_pos + 1) / ((self.neg + 0.1) / (self.n_neg + 1))
        good = np.flatnonzero((signed > chi) & (ratio > rate) & (self.pos >= 3))
        return good[np.argsort(-signed[good], kind="stable")][:most]


def mine(rows: DataFrame, n_pos: int, n_neg: int) -> Lexicon:
    fixed = insult_hashes()
    top = _counts(rows.where("y = 1")).where("n >= 3").orderBy(F.desc("n"), "h").limit(MAX_CANDIDATES).toArrow()
    keys = np.unique(np.concatenate([np.asarray(top["h"]).view(U64), fixed]))
    counts = []
    for y in (1, 0):
        got = _counts(rows.where(F.col("y") == y), keys).toArrow()  # at most a row per candidate
        n = np.zeros(len(keys), np.int64)
        n[np.searchsorted(keys, np.asarray(got["h"]).view(U64))] = np.asarray(got["n"])
        counts.append(n)
    return Lexicon(keys, *counts, n_pos, n_neg)


# ----------------------------------------------------------------- label model


@dataclass
class LabelModel:
    """Rates at which voters fire per class, and the weight of each voter."""

    prior: float
    hit: np.ndarray
    miss: np.ndarray
    share: np.ndarray

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        """Probability of the toxic class given rows of votes (fired or not)."""
        quiet = np.log((1 - self.hit) / (1 - self.miss))
        z = np.log(self.prior / (1 - self.prior)) + self.share @ quiet + votes @ (self.share * (np.log(self.hit / self.miss) - quiet))
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def vote_patterns(docs: DataFrame, voters: np.ndarray) -> DataFrame:
    """(votes, n): the sets of voters that fire together, packed as bits, and in how many texts."""
    shared, width = docs.sparkSession.sparkContext.broadcast(voters), len(voters) + SHAPES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in slices(batch.column(0)):
                votes = np.zeros((t.n, width), bool)
                votes[features(t, shared.value)] = True
                votes[:, width - SHAPES :] = shapes(t)
                seen, n = np.unique(np.packbits(votes, axis=1), axis=0, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([r.tobytes() for r in seen], pa.binary()), pa.array(n)], names=["votes", "n"])

    return docs.select("text").mapInArrow(resting(run), "votes binary, n long").groupBy("votes").agg(F.sum("n").alias("n"))


def _unpacked(batch: pa.RecordBatch, width: int) -> tuple[np.ndarray, np.ndarray]:
    bits = np.frombuffer(b"".join(batch.column(0).to_pylist()), np.uint8).reshape(len(batch.column(0)), -1)
    return np.unpackbits(bits, axis=1)[:, :width].astype(float), np.asarray(batch.column(1)).astype(float)


def label_model(patterns: DataFrame, width: int, start: LabelModel, rounds: int = ROUNDS) -> LabelModel:
    """Expectation maximisation over all vote patterns; a round is one small job whose result
    per task is one row of sums."""
    model = start
    for step in range(rounds):

        def sums(batches: Iterator[pa.RecordBatch], model: LabelModel = model) -> Iterator[pa.RecordBatch]:
            total = np.zeros(2 * width + 2)
            for batch in batches:
                v, n = _unpacked(batch, width)
                p = model.posterior(v) * n
                total += np.concatenate([p @ v, (n - p) @ v, [p.sum(), n.sum()]])
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["sums"])

        got = sum((np.frombuffer(r[0]) for r in patterns.mapInArrow(resting(sums), "sums binary").collect()), np.zeros(2 * width + 2))
        fired, quiet, (toxic, all_) = got[:width], got[width:-2], got[-2:]
        model = LabelModel(
            float(np.clip((toxic + ANCHOR * start.prior) / (all_ + ANCHOR), 1e-4, 0.95)),
            (fired + ANCHOR * start.hit) / (toxic + ANCHOR),
            (quiet + ANCHOR * start.miss) / (all_ - toxic + ANCHOR),
            model.share,
        )
        if step in (3, 8):
            model.share = _shares(patterns, width, model)
    return model


def _shares(patterns: DataFrame, width: int, model: LabelModel) -> np.ndarray:
    """Weight of each voter, less the more it repeats others beyond what the class explains."""

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((width, width))
        for batch in batches:
            v, n = _unpacked(batch, width)
            p = model.posterior(v)
            for w, rate in ((p * n, model.hit), ((1 - p) * n, model.miss)):
                both, alone = (v * w[:, None]).T @ v, w @ v
                total += both - np.outer(alone, rate) - np.outer(rate, alone) + w.sum() * np.outer(rate, rate)
        i, j = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(total[i, j])], names=["i", "j", "s"])

    cov = np.zeros((width, width))  # a few hundred voters at most
    for r in patterns.mapInArrow(resting(pairs), "i long, j long, s double").groupBy("i", "j").agg(F.sum("s").alias("s")).collect():
        cov[r["i"], r["j"]] = r["s"]
    dev = np.sqrt(np.maximum(np.diag(cov), 1e-9))
    corr = np.clip(cov / dev[:, None] / dev, 0, 1)
    np.fill_diagonal(corr, 0)
    return 1 / (1 + np.where(corr > 0.5, corr, 0).sum(axis=1))


# ------------------------------------------------------------------ classifier


@dataclass
class Model:
    keys: np.ndarray  # sorted feature hashes
    weights: np.ndarray
    bias: float
    voters: np.ndarray | None = None  # the label model and its voters, where there is one
    labels: LabelModel | None = None


def _linear(own: np.ndarray, col: np.ndarray, n: int, k: int, y: np.ndarray, weight: np.ndarray, rounds: int = 500) -> tuple[np.ndarray, float]:
    """Logistic regression on sparse 0/1 features by accelerated gradient steps."""
    w, b = np.zeros(k), float(np.log((weight @ y + 1) / (weight @ (1 - y) + 1)))
    vw, vb, total = w.copy(), b, weight.sum()
    size = np.bincount(own, minlength=n)
    step = 4.0 / (1 + np.percentile(size, 99)) if n else 1.0
    lam = 2e-5
    for i in range(rounds):
        z = vb + np.bincount(own, weights=vw[col], minlength=n)
        g = weight * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) / total
        nw = vw - step * 8 * (np.bincount(col, weights=g[own], minlength=k) + lam * vw)
        nb = vb - step * g.sum()
        m = i / (i + 3)
        vw, vb = nw + m * (nw - w), nb + m * (nb - b)
        w, b = nw, nb
    return w, b


def training_labels(labels: DataFrame) -> DataFrame:
    """(doc_id, y): labels outside the held-out quarter."""
    rows = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    return rows.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("y"))


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    fixed = insult_hashes()
    plain = Model(np.sort(fixed), np.full(len(fixed), 4.0), -3.0)
    rows = labelled(docs, training_labels(labels))
    counts = dict(rows.groupBy("y").count().collect())
    if not counts.get(0) or not counts.get(1):
        return plain
    lexicon = mine(rows, counts[1], counts[0])
    voters = np.sort(np.union1d(lexicon.keys[lexicon.standing_out(*VOTER, MAX_VOTERS)], fixed))
    at, width = np.searchsorted(lexicon.keys, voters), len(voters) + SHAPES
    keep = np.sort(np.union1d(lexicon.keys[lexicon.standing_out(*FEATURE, MAX_FEATURES)], voters))
    # the bounded sample: its texts' features and votes
    picked = [rows.where(F.col("y") == y).select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(MAX_LABELLED) for y in (0, 1)]
    chosen = picked[0].unionByName(picked[1]).collect()  # at most twice MAX_LABELLED ids
    ids = docs.sparkSession.createDataFrame([(r[0],) for r in chosen], "label_id long")
    shared = docs.sparkSession.sparkContext.broadcast((keep, voters))

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, some = shared.value
        for batch in batches:
            for t in slices(batch.column(1)):
                own, slot = features(t, keys)
                cut = np.searchsorted(own, np.arange(t.n + 1))
                votes = np.zeros((t.n, len(some) + SHAPES), bool)
                votes[features(t, some)] = True
                votes[:, len(some) :] = shapes(t)
                bits = np.packbits(votes, axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(t.first, t.n), pa.array([slot[a:b].astype(np.int32).tobytes() for a, b in zip(cut, cut[1:], strict=False)], pa.binary()), pa.array([r.tobytes() for r in bits], pa.binary())], names=["y", "features", "votes"])

    sample = rows.join(F.broadcast(ids), F.col("doc_id") == F.col("label_id")).select("y", "text").mapInArrow(resting(look), "y int, features binary, votes binary").toArrow()
    y, n = sample["y"].to_numpy().astype(float), len(sample)
    blobs = sample["features"].to_pylist()
    own = np.repeat(np.arange(n), [len(b) // 4 for b in blobs])
    col = np.frombuffer(b"".join(blobs), np.int32)
    bits = np.frombuffer(b"".join(sample["votes"].to_pylist()), np.uint8).reshape(n, -1)
    votes = np.unpackbits(bits, axis=1)[:, :width].astype(float)
    prior = counts[1] / (counts[0] + counts[1])
    # rates to start from: the lexicon's counts, and the sample's where a voter is no word
    hit = np.concatenate([(lexicon.pos[at] + 0.1) / (counts[1] + 1), (y @ votes[:, len(voters) :] + 0.1) / (y.sum() + 1)])
    miss = np.concatenate([(lexicon.neg[at] + 0.1) / (counts[0] + 1), ((1 - y) @ votes[:, len(voters) :] + 0.1) / ((1 - y).sum() + 1)])
    training = docs.where(~held_out(F.col("doc_id").cast("long")))
    patterns = persisted(vote_patterns(training, voters).repartition(max(1, shuffle_width(docs.sparkSession) // 2)), "votes")
    model = label_model(patterns, width, LabelModel(prior, hit, miss, np.ones(width)))
    discard(patterns)
    posterior = model.posterior(votes)
    # classes are sampled alike; weights bring back their shares among the labelled rows
    weight = np.where(y == 1, prior / y.mean(), (1 - prior) / (1 - y.mean()))
    w, b = _linear(own, col, n, len(keep), posterior, weight)
    return Model(keep, w, b, voters, model)


def score_texts(t: Texts, model: Model) -> np.ndarray:
    """Scores of the documents of a slice."""
    own, slot = features(t, model.keys)
    total = model.bias + np.bincount(own, weights=model.weights[slot], minlength=t.n)
    return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def score(docs: DataFrame, model: Model, column: str = "toxic_score") -> DataFrame:
    """All columns of ``docs`` and the score of ``text``, in a column whose name none of them has
    (``column``, with underscores after it where that is taken)."""
    at, column = docs.columns.index("text"), fresh_name(docs, column)
    schema = T.StructType([*docs.schema.fields, T.StructField(column, T.DoubleType())])
    small = Model(model.keys, model.weights, model.bias)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = [score_texts(t, small) for t in slices(batch.column(at))]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(parts) if parts else [], pa.float64())], names=[*batch.schema.names, column])

    return docs.mapInArrow(resting(run), schema)


def toxicity_digests(docs: DataFrame, labels: DataFrame) -> DataFrame:
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    got = score(docs, fit(docs, labels), "score")
    return got.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
