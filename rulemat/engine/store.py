"""Fact stores on shared storage.

A relation is a set of rows kept in Parquet parts that are disjoint; a fact store maps
predicates to relations; a bag is a list of stores, read as their union and never merged.
Handles are immutable: an update makes new handles and the old ones stay readable, so a failed
update leaves the old state whole.
"""

from __future__ import annotations

import itertools
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..sharing import shared_root


class Storage:
    """Where parts are written: below ``shared_root``.  ``cut`` is ``parquet`` or ``checkpoint``."""

    def __init__(self, spark: SparkSession, cut: str = "parquet", root: str | None = None):
        if cut not in ("parquet", "checkpoint"):
            raise ValueError(f"unknown cut {cut}")
        self.spark, self.cut = spark, cut
        self.root = f"{(root or shared_root(spark)).rstrip('/')}/facts-{uuid.uuid4().hex[:12]}"
        if cut == "checkpoint" and spark.sparkContext.getCheckpointDir() is None:
            spark.sparkContext.setCheckpointDir(f"{self.root}/checkpoints")
        self.written = itertools.count(1)  # its steps are atomic, so nodes may run in threads
        self._sorted: dict[tuple[int, str], Part] = {}

    def write(self, df: DataFrame) -> Part:
        """Materialise a frame and count its rows in the same job."""
        seen = Observation()
        watched = df.observe(seen, F.count(F.lit(1)).alias("n"))
        if self.cut == "checkpoint":
            made = watched.checkpoint(eager=True)
            return Part(made, made.count(), None)
        path = f"{self.root}/{next(self.written):06d}"
        watched.write.parquet(path)
        return Part(self.spark.read.schema(df.schema).parquet(path), int(seen.get["n"]), path)

    def sorted_by(self, part: Part, column: str) -> DataFrame:
        """A part in the order of a column: written once, so that reads of ranges and single
        values of the column skip most of its files."""
        key = (id(part), column)
        if key not in self._sorted:
            copy = self.write(part.frame.repartitionByRange(column).sortWithinPartitions(column))
            self._sorted[key] = Part(copy.frame, part.rows, copy.path, of=part)  # keeps the part, hence its id
        return self._sorted[key].frame

    def vacuum(self, live: set[str]) -> int:
        """Delete written parts that no live handle names, with their sorted copies."""
        self._sorted = {k: c for k, c in self._sorted.items() if c.of.path is not None and c.of.path in live}
        live = live | {c.path for c in self._sorted.values() if c.path}
        hpath = self.spark._jvm.org.apache.hadoop.fs.Path
        fs = hpath(self.root).getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(hpath(self.root)):
            return 0
        gone = [str(s.getPath().getName()) for s in fs.listStatus(hpath(self.root)) if f"{self.root}/{s.getPath().getName()}" not in live]
        for name in gone:
            fs.delete(hpath(f"{self.root}/{name}"), True)
        return len(gone)


@dataclass(frozen=True, eq=False)
class Part:
    """Rows at rest.  A part with ``labels`` stands for all pairs of nodes that have the same
    label: ``path`` holds the labels (node, component), and ``frame`` pairs them when read.  One
    with ``ranks`` (node, component, left) stands for the pairs that follow each other on a chain.
    A ``lazy`` part is a difference between states: counted, but not written.  ``every`` gives the
    rows of ``frame`` to a reader of all of them, if there is a faster way to that."""

    frame: DataFrame
    rows: int
    path: str | None
    labels: DataFrame | None = None
    of: Part | None = None
    ranks: DataFrame | None = None
    lazy: bool = False
    every: DataFrame | None = None

    @property
    def closed(self) -> bool:
        return self.labels is not None or self.ranks is not None


@dataclass(frozen=True, eq=False)
class Relation:
    parts: tuple[Part, ...] = ()

    @property
    def rows(self) -> int:
        return sum(p.rows for p in self.parts)

    def frame(self) -> DataFrame | None:
        live = [p.frame for p in self.parts if p.rows]
        out = live[0] if live else None
        for f in live[1:]:
            out = out.unionByName(f)
        return out

    def plus(self, part: Part) -> Relation:
        return Relation((*self.parts, part)) if part.rows else self


EMPTY = Relation()


@dataclass
class FactStore:
    relations: dict[str, Relation] = field(default_factory=dict)

    def get(self, pred: str) -> Relation:
        return self.relations.get(pred, EMPTY)

    def put(self, pred: str, relation: Relation) -> FactStore:
        return FactStore(self.relations | {pred: relation})

    def preds(self) -> list[str]:
        return [p for p, r in self.relations.items() if r.rows]

    @property
    def rows(self) -> int:
        return sum(r.rows for r in self.relations.values())

    def paths(self) -> set[str]:
        return {p.path for r in self.relations.values() for p in r.parts if p.path}


class StoreBag:
    """Named stores with an index from predicates to the stores that hold them."""

    def __init__(self, stores: dict[str, FactStore]):
        self.stores = stores
        self.index: dict[str, list[str]] = {}
        for name, s in stores.items():
            for pred in s.preds():
                self.index.setdefault(pred, []).append(name)

    def members(self, pred: str) -> list[str]:
        return self.index.get(pred, [])

    def union(self, other: StoreBag) -> StoreBag:
        """Pointers only: nothing is read or written."""
        return StoreBag(self.stores | other.stores)

    def relation(self, pred: str, without: frozenset[str] = frozenset()) -> DataFrame | None:
        """Union of the members' relations; duplicates are dropped where two members meet."""
        if (whole := self.covering(pred, without)) is not None:
            return whole.frame
        frames = [self.stores[n].get(pred).frame() for n in self.members(pred) if n not in without]
        frames = [f for f in frames if f is not None]
        if not frames:
            return None
        out = frames[0]
        for f in frames[1:]:
            out = out.unionByName(f)
        return out.distinct() if len(frames) > 1 else out

    def covering(self, pred: str, without: frozenset[str] = frozenset()) -> Part | None:
        """The closed form that holds every fact of ``pred``: a closure's store is closed over
        all other stores of its predicate, so nothing has to be added or compared."""
        for n in self.members(pred):
            parts = [p for p in self.stores[n].get(pred).parts if p.rows] if n not in without else []
            if len(parts) == 1 and parts[0].closed:
                return parts[0]
        return None

    def missing(self, df: DataFrame, pred: str, without: frozenset[str] = frozenset()) -> DataFrame:
        """Rows that are no fact of ``pred``.  A pair is looked up in labels, not in their pairs."""
        plain: DataFrame | None = None
        whole = self.covering(pred, without)
        for part in (p for n in self.members(pred) if n not in without for p in self.stores[n].get(pred).parts if p.rows):
            if whole is not None and part is not whole:
                continue
            if part.labels is None:
                plain = part.frame if plain is None else plain.unionByName(part.frame)
                continue
            side = lambda c: part.labels.select(F.col("node").alias(c), F.col("component").alias(f"{c}_label"))  # noqa: B023, E731
            apart = ~F.coalesce(F.col("c0_label") == F.col("c1_label"), F.lit(False))
            df = df.join(side("c0"), "c0", "left").join(side("c1"), "c1", "left").where(apart).select("c0", "c1")
        return df if plain is None else df.join(plain, df.columns, "left_anti")

    def rows(self, pred: str) -> int:
        return sum(self.stores[n].get(pred).rows for n in self.members(pred))

    def ordered(self, pred: str, by: str, storage: Storage, without: frozenset[str] = frozenset()) -> DataFrame | None:
        """The relation from copies of its parts in the order of one column; labels have no
        copies, as their pairs are never stored."""
        parts = [p for n in self.members(pred) if n not in without for p in self.stores[n].get(pred).parts if p.rows]
        if not parts:
            return None
        if (whole := self.covering(pred, without)) is not None:
            return whole.frame
        frames = [p.frame if p.closed or by not in p.frame.columns else storage.sorted_by(p, by) for p in parts]
        out = frames[0]
        for f in frames[1:]:
            out = out.unionByName(f)
        return out.distinct() if sum(n not in without for n in self.members(pred)) > 1 else out
