"""Graph helpers over edge tables that never leave the cluster."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .slices import SLICE, stars, tails

#: Edges between slices that one task joins; more go through rounds of Spark jobs.
FEW_LINKS = 100_000


def components(edges: DataFrame, cut: Callable[[DataFrame, str], DataFrame]) -> DataFrame:
    """(node, component): the smallest node that each node of ``edges`` (a, b) reaches.

    Every round gives a node the least label among its own, its neighbours', its label's label
    (pointer jumping) and, if it is a label itself, all that its bearers see (hooking), until
    nothing changes.  Labels only fall, so this ends.  Paths of 10,000 shuffled nodes took 18
    rounds in a model of this loop, paths of 1,000,000 took 27.  Minima are combined before the
    shuffle, so hubs are harmless.  ``cut`` materialises a frame and cuts its lineage.
    """
    e = edges.where(F.col("a") != F.col("b")).select("a", "b")
    both = cut(e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("component")), "labels")
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), F.col("component").alias("other")), "b").groupBy(F.col("a").alias("node")).agg(F.min("other").alias("near"))
        stepped = cut(labels.join(near, "node").select("node", F.col("component").alias("old"), F.least("component", "near").alias("new")), "labels")
        if stepped.where(F.col("old") != F.col("new")).isEmpty():
            break
        hooks = stepped.groupBy(F.col("old").alias("node")).agg(F.min("new").alias("hook"))
        rooted = stepped.join(hooks, "node", "left").select("node", F.least("new", F.coalesce("hook", "new")).alias("new"))
        jumped = rooted.join(labels.select(F.col("node").alias("new"), F.col("component").alias("far")), "new", "left").select("node", F.least("new", F.coalesce("far", "new")).alias("component"))
        labels = cut(jumped, "labels")
    return labels


def contracted(edges: DataFrame, cut: Callable[[DataFrame, str], DataFrame], rows: int | None = None) -> DataFrame:
    """(node, component) as of ``components``, nodes with nothing but a loop included, in a few
    jobs: tasks join the edges of a range of nodes, and only links between ranges go on, to one
    task if they are few, else to ``components``.  Edges known to be at most ``rows``, if that is
    one slice, are joined by one task, when read."""
    kind = dict(edges.dtypes)["a"]
    joined = lambda df: df.mapInArrow(stars, f"node {kind}, root {kind}")
    if rows is not None and rows <= SLICE:
        return joined(edges.select("a", "b").repartition(1)).toDF("node", "component")
    forest = cut(joined(edges.select("a", "b").repartitionByRange("a")), "forest")
    lows = forest.groupBy("node").agg(F.min("root").alias("low"), F.collect_set("root").alias("roots"))
    lows = cut(lows.select("node", "low", F.when(F.size("roots") > 1, F.col("roots")).alias("roots")), "lows")
    links = cut(lows.select(F.explode("roots").alias("a"), F.col("low").alias("b")).where("a <> b").distinct(), "links")
    n = links.count()
    if not n:
        return lows.select("node", F.col("low").alias("component"))
    merged = joined(links.coalesce(1)) if n <= FEW_LINKS else components(links, cut).toDF("node", "root")
    merged = merged.select(F.col("node").alias("low"), "root")
    return lows.join(merged, "low", "left").select("node", F.coalesce("root", "low").alias("component"))


def bfs_levels(edges: DataFrame, sources: DataFrame, max_depth: int, cut: Callable[[DataFrame, str], DataFrame]) -> DataFrame:
    """(node, level): fewest steps along edges (a, b) from any source, up to a depth."""
    seen = cut(sources.select("node").distinct().withColumn("level", F.lit(0)), "level")
    front = seen
    for depth in range(1, max_depth + 1):
        step = front.join(edges, F.col("node") == F.col("a")).select(F.col("b").alias("node")).distinct()
        front = cut(step.join(seen, "node", "left_anti").withColumn("level", F.lit(depth)), "level")
        if front.isEmpty():
            break
        seen = seen.unionByName(front)
    return seen


def degree(edges: DataFrame) -> DataFrame:
    """(node, degree) over both ends of edges (a, b)."""
    ends = edges.select(F.col("a").alias("node")).unionByName(edges.select(F.col("b").alias("node")))
    return ends.groupBy("node").agg(F.count("*").alias("degree"))


def scc(edges: DataFrame, cut: Callable[[DataFrame, str], DataFrame]) -> DataFrame:
    """(node, component): strongly connected components of a data relation by repeated
    forward and backward colouring: the nodes that reach and are reached by a colour's root
    form a component and leave.  Before each colouring, nodes without an edge in or without an
    edge out leave as components of their own.  Ends when no node is left."""
    left = cut(edges.where(F.col("a") != F.col("b")).select("a", "b").distinct(), "edges")
    nodes = cut(edges.select(F.col("a").alias("node")).unionByName(edges.select(F.col("b").alias("node"))).distinct(), "nodes")
    parts: list[DataFrame] = []

    def settle(part: DataFrame) -> None:
        parts.append(part)
        if len(parts) == 16:  # plans stay short
            parts[:] = [cut(reduce(DataFrame.unionByName, parts), "part")]

    def within(e: DataFrame) -> DataFrame:
        keep = lambda side: nodes.select(F.col("node").alias(side))
        return cut(e.join(keep("a"), "a", "left_semi").join(keep("b"), "b", "left_semi"), "edges")

    while True:
        inner = cut(left.select(F.col("a").alias("node")).intersect(left.select(F.col("b").alias("node"))), "nodes")
        ends = cut(nodes.join(inner, "node", "left_anti").select("node", F.col("node").alias("component")), "part")
        if not ends.isEmpty():
            settle(ends)
            nodes = inner
            left = within(left)
            continue
        if nodes.isEmpty():
            break
        colour = cut(nodes.withColumn("colour", F.col("node")), "colour")
        while True:
            near = left.join(colour.select(F.col("node").alias("a"), "colour"), "a").groupBy(F.col("b").alias("node")).agg(F.min("colour").alias("c2"))
            nxt = cut(colour.join(near, "node", "left").select("node", F.col("colour").alias("old"), F.least("colour", F.coalesce("c2", "colour")).alias("colour")), "colour")
            moved = not nxt.where(F.col("old") != F.col("colour")).isEmpty()
            colour = nxt.select("node", "colour")
            if not moved:
                break
        back = cut(colour.where(F.col("node") == F.col("colour")), "back")
        inside = left.join(colour.select(F.col("node").alias("a"), F.col("colour").alias("ca")), "a").join(colour.select(F.col("node").alias("b"), F.col("colour").alias("cb")), "b").where(F.col("ca") == F.col("cb")).select("a", "b", F.col("ca").alias("colour"))
        front = back
        while not front.isEmpty():
            step = inside.join(front.select(F.col("node").alias("b"), "colour"), ["b", "colour"]).select(F.col("a").alias("node"), "colour").distinct()
            front = cut(step.join(back, ["node", "colour"], "left_anti"), "front")
            back = back.unionByName(front)
        part = cut(back.select("node", F.col("colour").alias("component")), "part")
        settle(part)
        nodes = cut(nodes.join(part, "node", "left_anti"), "nodes")
        left = within(left)
    return reduce(DataFrame.unionByName, parts) if parts else nodes.select("node", F.col("node").alias("component"))


#: Pairs that one task makes, and rows that a broadcast of one side may have.
PAIRS_A_TASK, BROADCAST_ROWS, SALTS = 4_000_000, 2_000_000, 64
#: Nodes of a run: fewer make c0 change more often, more make c1 take longer to repeat.
TILE = 256


def paired(left: DataFrame, right: DataFrame, by: str, n: int, pairs: int) -> DataFrame:
    """Join of two small tables of ``n`` rows on ``component`` that makes many pairs: the left
    side is dealt over tasks by its column ``by``, so that few large components fill all of them."""
    if n > BROADCAST_ROWS:
        a = left.withColumn("_salt", F.pmod(F.xxhash64(by), F.lit(SALTS)).cast("int"))
        b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        return a.join(b.hint("shuffle_hash"), ["component", "_salt"]).drop("_salt")
    tasks = min(pairs // PAIRS_A_TASK + 1, 4096)
    return (left.repartition(tasks, by) if tasks > 1 else left).join(F.broadcast(right), "component")


def tiled_pairs(nodes: DataFrame, n: int, pairs: int, after: bool = False) -> DataFrame:
    """(c0, c1): all pairs of (node, component) with the same component, from a table of ``n``
    rows, for a reader of all of them; with ``after`` only a node and those that follow it on its
    chain, from (node, component, left).  A component's nodes go in runs of ``TILE``, and runs meet
    in a join instead of nodes: each node of one run is put before the whole other run.  So c0 stays
    the same and c1 repeats for long stretches, which a file of all pairs holds in a fortieth."""
    place = F.row_number().over(Window.partitionBy("component").orderBy(F.desc("left") if after else F.asc("node"))) - 1
    held = nodes.select("component", "node", place.alias("place")).groupBy("component", F.floor(F.col("place") / TILE).alias("run"))
    runs = held.agg(F.sort_array(F.collect_list(F.struct("place", "node"))).alias("at")).select("component", "run", F.col("at.node").alias("nodes"))
    # a task gets whole runs of c1, as few different ones as it can
    ends = runs.select("component", "run", "nodes", F.col("nodes")[0].alias("head"))
    begins = runs.select("component", F.col("run").alias("from"), F.col("nodes").alias("before"))
    tiles = paired(ends, begins, "head", n, pairs)
    # coalesce leaves the tasks as they are, and parts the code that Spark generates: in one piece,
    # it would hold all pairs of a row before it gives the first
    apart = lambda df: df.coalesce(1_000_000)
    if not after:
        rows = apart(tiles).select(F.explode("before").alias("c0"), "nodes")
    else:
        rows = apart(tiles.where(F.col("from") <= F.col("run"))).select("from", "run", "nodes", F.posexplode("before").alias("k", "c0"))
        rest = F.when(F.col("from") == F.col("run"), F.slice("nodes", F.col("k") + 2, F.lit(TILE))).otherwise(F.col("nodes"))
        rows = rows.select("c0", rest.alias("nodes"))
    return apart(rows).select("c0", F.explode("nodes").alias("c1"))


def chain_ranks(edges: DataFrame, cut: Callable[[DataFrame, str], DataFrame]) -> DataFrame | None:
    """(node, component, left): the last node of each node's chain and the steps left to it, if
    the edges (a, b) are nothing but chains; else None.  Tasks follow the edges of a range of
    nodes; what leads on from one range to another is followed by one task if it is little, else
    by rounds that double the steps."""
    e = cut(edges.select("a", "b").distinct(), "edges")
    ways = e.groupBy(F.col("a").alias("node")).agg(F.count("*").alias("n")).unionByName(e.groupBy(F.col("b").alias("node")).agg(F.count("*").alias("n")))
    if ways.agg(F.max("n")).first()[0] != 1:
        return None
    kind = dict(e.dtypes)["a"]
    followed = lambda df: df.mapInArrow(tails, f"node {kind}, last {kind}, left long")
    parts = cut(followed(e.withColumn("left", F.lit(1).cast("long")).repartitionByRange("a")), "tails")
    on = cut(parts.join(parts.select(F.col("last").alias("node")).distinct(), "node", "left_semi"), "tails")
    n, least = on.agg(F.count("*"), F.min("left")).first()
    if n and n <= FEW_LINKS:
        on = cut(followed(on.select(F.col("node").alias("a"), F.col("last").alias("b"), "left").coalesce(1)), "tails")
        least = on.agg(F.min("left")).first()[0]
    elif n and least > 0:
        on = _doubled(on, n, cut)
    if on is None or (n and least < 0):  # a circle leads back to its own nodes, so ``on`` has some
        return None
    far = on.select(F.col("node").alias("last"), F.col("last").alias("far"), F.col("left").alias("more"))
    ranks = parts.join(far, "last", "left").select("node", F.coalesce("far", "last").alias("component"), (F.col("left") + F.coalesce("more", F.lit(0).cast("long"))).alias("left"))
    last = e.select(F.col("b").alias("node")).join(e.select(F.col("a").alias("node")), "node", "left_anti")
    return ranks.unionByName(last.select("node", F.col("node").alias("component"), F.lit(0).cast("long").alias("left")))


def _doubled(on: DataFrame, nodes: int, cut: Callable[[DataFrame, str], DataFrame]) -> DataFrame | None:
    """Steps (node, last, left) led on to where no step leads on; None if some never end."""
    steps = 1
    while True:
        far = on.select(F.col("node").alias("last"), F.col("last").alias("far"), F.col("left").alias("more"))
        on = cut(on.join(far, "last", "left").select("node", F.coalesce("far", "last").alias("last"), (F.col("left") + F.coalesce("more", F.lit(0).cast("long"))).alias("left"), F.col("far").isNotNull().alias("moved")), "tails")
        if on.where("moved").isEmpty():
            return on.select("node", "last", "left")
        if steps > nodes:  # more steps than nodes: a circle
            return None
        steps *= 2


def ranked_pairs(first: DataFrame, second: DataFrame, n: int, pairs: int) -> DataFrame:
    """(a, b): nodes of ``first`` and those of ``second`` that follow them on their chain."""
    side = lambda df, c: df.select(F.col("node").alias(c), "component", F.col("left").alias(f"{c}_left"))
    return paired(side(first, "a"), side(second, "b"), "a", n, pairs).where("a_left > b_left").select("a", "b")


def closure(edges: DataFrame, cut: Callable[[DataFrame, str], DataFrame], chains: bool = True) -> DataFrame:
    """(a, b): all pairs joined by a path.  Chains are ranked, and their pairs made when read.
    Else by doubling: paths of exactly 2**k edges go before all paths of at most as many, so a
    path of n edges takes log2(n) rounds, and one that is the only one is found once."""
    if chains and (ranks := chain_ranks(edges, cut)) is not None:
        ranks = cut(ranks, "ranks")
        n, pairs = ranks.agg(F.count("*"), F.sum("left")).first()
        return tiled_pairs(ranks, n, pairs or 0, after=True).toDF("a", "b")
    exact = cut(edges.select("a", "b").distinct(), "paths")
    known = fresh = exact
    ends = lambda df, x, y: df.select(F.col("a").alias(x), F.col("b").alias(y))
    while True:
        longer = ends(exact, "a", "m").join(ends(known, "m", "b"), "m").select("a", "b").distinct()
        fresh = cut(longer.join(known, ["a", "b"], "left_anti"), "paths")
        if fresh.isEmpty():
            return known
        known = known.unionByName(fresh)
        exact = cut(ends(exact, "a", "m").join(ends(exact, "m", "b"), "m").select("a", "b").distinct(), "paths")


def ancestors(edges: DataFrame, nodes: DataFrame, cut: Callable[[DataFrame, str], DataFrame]) -> DataFrame:
    """(node, ancestor): what lies upstream of given nodes along edges (a, b).  On chains it is
    read from ranks.  Else only the given nodes' paths are followed, so a few nodes of a large
    graph stay cheap: one level a round, and after ten rounds by steps of doubled length, unless
    these become many more than the edges."""
    if (ranks := chain_ranks(edges, cut)) is not None:
        ranks = cut(ranks, "ranks")
        wanted = cut(ranks.join(nodes.select("node").distinct(), "node", "left_semi"), "nodes")
        most, n = ranks.agg(F.max("left"), F.count("*")).first()
        return ranked_pairs(ranks, wanted, n, most * wanted.count()).select(F.col("b").alias("node"), F.col("a").alias("ancestor"))
    front = cut(nodes.select("node").distinct().withColumn("at", F.col("node")), "front")
    up = cut(edges.select(F.col("b").alias("at"), F.col("a").alias("to")).distinct(), "steps")
    limit, rounds, step = 4 * max(1000, up.count()), 0, up
    seen = front.limit(0)
    while True:
        front = cut(front.join(step, "at").select("node", F.col("to").alias("at")).distinct().join(seen, ["node", "at"], "left_anti"), "front")
        if front.isEmpty():
            break
        seen = cut(seen.unionByName(front), "seen")
        rounds += 1
        if rounds < 10 or step is None:
            continue
        # from here on all that is seen goes as far again; ``step`` are walks of 2**k edges
        while step.count() <= limit:
            new = cut(seen.join(step, "at").select("node", F.col("to").alias("at")).distinct().join(seen, ["node", "at"], "left_anti"), "front")
            if new.isEmpty():
                return seen.select("node", F.col("at").alias("ancestor"))
            seen = cut(seen.unionByName(new), "seen")
            step = cut(step.join(step.select(F.col("at").alias("to"), F.col("to").alias("far")), "to").select("at", F.col("far").alias("to")).distinct(), "steps")
        front, step, rounds = seen, up, -(10**9)  # too many: level by level again
    return seen.select("node", F.col("at").alias("ancestor"))
