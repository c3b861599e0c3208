"""Approximate nearest neighbours by inner product: NN-descent and greedy graph search.

The graph starts from overlapping cells around random pivots, in which all pairs are compared.
Rounds of NN-descent improve it with joins: the vectors of a node's neighbours, forward and
reverse, are brought together at the node, compared with each other, and each pair that beats a
neighbour list it could enter is sent to the list's owner. Queries then walk the graph greedily,
a bounded number of nodes wide, until their lists stop changing.

Equal vectors are one node, so a vector that very many rows share is no hub. Inner products are
turned into distances by one more coordinate that gives all nodes the same norm.

A cell that is too large for a task is dealt into slices by the order of its vectors along a
random direction, another one for each set of pivots, so that near vectors meet in some slice;
what the cells have missed, the rounds find.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from llm.store import drop, keep, release, table, workspace

#: Neighbours that a node keeps.
DEGREE = 28
#: Nodes in a cell on average, and at most in one task; larger cells are dealt into parts.
CELL, CELL_MAX = 1500, 5000
#: Cells a node belongs to, and sets of pivots. Pivots are MAX_PIVOTS at most.
OVERLAP, PIVOT_SETS, MAX_PIVOTS = 3, 4, 4096
#: Neighbours of each direction that a round of NN-descent brings together at a node.
FORWARD, REVERSE = 8, 6
#: Rounds go on as long as they change more than this share of all list entries.
SETTLED = 0.01
#: Quantiles that cut a large cell into slices.
SLICES = 256
#: Width of a query's list, nodes it expands in a round, and neighbours it looks at of each.
BEAM, EXPAND, LOOK = 48, 12, 16

LIST = "array<struct<sim:float,id:long>>"


def usable(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(vec_id, v): rows with an id and a vector of finite components that is not zero and has the most common dimension."""
    v = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v")).where("vec_id is not null and v is not null and size(v) > 0")
    v = v.where("forall(v, x -> x is not null and not isnan(x) and abs(x) < double('Infinity')) and exists(v, x -> x <> 0)")
    top = v.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    return v.where(F.size("v") == (top[0]["d"] if top else 0))


def nodes_of(vectors: DataFrame, members: int) -> DataFrame:
    """One node for each distinct vector: id (its smallest vec_id), v, and its `members` smallest ids; the limit is applied where rows are read, so a common vector is not gathered."""
    w = Window.partitionBy("v").orderBy("vec_id")
    few = vectors.distinct().withColumn("r", F.row_number().over(w)).where(F.col("r") <= members)
    return few.groupBy("v").agg(F.min("vec_id").alias("id"), F.array_sort(F.collect_list("vec_id")).alias("members"))


def _matrix(column, dim: int | None = None) -> np.ndarray:
    return np.array(column.tolist(), dtype=np.float64) if len(column) else np.zeros((0, dim or 1))


def lift(x: np.ndarray, top: float) -> np.ndarray:
    """The vectors with a coordinate that brings all to the norm `top`; between such vectors the nearest has the largest inner product."""
    return np.concatenate([x, np.sqrt(np.maximum(0, top * top - (x * x).sum(axis=1)))[:, None]], axis=1)


def _best(sims: np.ndarray, k: int) -> np.ndarray:
    """Columns of the k largest entries of each row."""
    k = min(k, sims.shape[1])
    return np.argpartition(-sims, k - 1, axis=1)[:, :k]


def _lists(ids: np.ndarray, cols: np.ndarray, sims: np.ndarray) -> list[list[dict]]:
    return [[{"sim": float(s), "id": int(ids[c])} for c, s in zip(cs, ss, strict=True) if np.isfinite(s)] for cs, ss in zip(cols.tolist(), sims.tolist(), strict=True)]


def cell_graph(nodes: DataFrame, count: int, top: float, degree: int = DEGREE) -> DataFrame:
    """(id, near): neighbour lists from the cells; a node has one row for each of its cells."""
    cells = int(min(MAX_PIVOTS, max(1, count // CELL)))
    overlap = min(OVERLAP, cells)
    sets = PIVOT_SETS if cells > overlap else 1
    pivots = []
    for s in range(sets):  # MAX_PIVOTS vectors at most
        pivots.append(lift(_matrix(nodes.orderBy(F.xxhash64("id", F.lit(s)), "id").limit(cells).select("v").toPandas()["v"]), top))

    ways = np.random.default_rng(29).normal(size=(sets, pivots[0].shape[1]))

    @F.pandas_udf("array<struct<cell:long,along:float>>")
    def cells_of(v: pd.Series) -> pd.Series:
        if not len(v):
            return pd.Series([], dtype=object)
        x, out = lift(_matrix(v), top), [[] for _ in range(len(v))]
        for s, p in enumerate(pivots):
            along = (x @ ways[s]).tolist()
            for i, own in enumerate((_best(x @ p.T, overlap) + s * cells).tolist()):
                out[i] += [{"cell": c, "along": along[i]} for c in own]
        return pd.Series(out)

    placed = nodes.select("id", "v", F.explode(cells_of("v")).alias("c")).select("id", "v", "c.cell", "c.along")
    large = placed.groupBy("cell").agg(F.count("*").alias("n"), F.percentile_approx("along", [k / SLICES for k in range(1, SLICES)], 10_000).alias("cuts")).where(F.col("n") > CELL_MAX)
    # as many slices as needed, each some neighbouring quantiles; a cell of more than SLICES * CELL_MAX is dealt further by hash
    large = large.select("cell", F.least(F.lit(SLICES), F.ceil(F.col("n") / CELL_MAX)).cast("int").alias("slices"), F.ceil(F.col("n") / (SLICES * CELL_MAX)).cast("int").alias("dealt"), "cuts")
    at = F.size(F.filter("cuts", lambda q: q < F.col("along")))
    placed = placed.join(large, "cell", "left").withColumn("part", F.coalesce(F.floor(at * F.col("slices") / SLICES) * F.col("dealt") + F.pmod(F.xxhash64("id", "cell"), F.col("dealt")), F.lit(0)).cast("int")).drop("slices", "dealt", "cuts", "along")

    def compare(df: pd.DataFrame) -> pd.DataFrame:
        ids, x = df["id"].to_numpy(), lift(_matrix(df["v"]), top)
        out = []
        for a in range(0, len(x), 1024):
            sims = x[a : a + 1024] @ x.T
            sims[np.arange(len(sims)), np.arange(a, a + len(sims))] = -np.inf
            cols = _best(sims, degree)
            out += _lists(ids, cols, np.take_along_axis(sims, cols, axis=1))
        return pd.DataFrame({"id": ids, "near": out})

    return placed.groupBy("cell", "part").applyInPandas(compare, f"id long, near {LIST}")


def merge_lists(lists: DataFrame, degree: int = DEGREE) -> DataFrame:
    """One list for each id: the best `degree` of all its lists (their number is bounded by the cells of a node and the updates of a round)."""
    return lists.groupBy("id").agg(F.expr(f"slice(sort_array(array_distinct(flatten(collect_list(near))), false), 1, {degree})").alias("near"))


def descend(nodes: DataFrame, graph: DataFrame, top: float, degree: int = DEGREE) -> DataFrame:
    """One round of NN-descent: neighbours of neighbours, compared where they meet."""
    ahead = graph.select("id", F.explode(F.slice("near", 1, FORWARD)).alias("e")).select("id", F.col("e.id").alias("to"), F.col("e.sim").alias("sim"))
    # of those that point at a node only the nearest few, chosen before they are gathered
    w = Window.partitionBy("to").orderBy(F.desc("sim"), "id")
    behind = ahead.withColumn("r", F.row_number().over(w)).where(F.col("r") <= REVERSE)
    meet = ahead.select("id", "to").union(behind.select(F.col("to").alias("id"), F.col("id").alias("to"))).distinct()
    worst = graph.select(F.col("id").alias("to"), F.when(F.size("near") >= degree, F.element_at("near", -1)["sim"]).alias("worst"))
    brought = meet.join(nodes.select(F.col("id").alias("to"), "v").join(worst, "to"), "to")

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for df in batches:
            owner, near = [], []
            for to, v, worst in zip(df["to"], df["v"], df["worst"], strict=True):
                ids, x = np.array(to), lift(np.array([np.array(a) for a in v], dtype=np.float64), top)
                sims = x @ x.T
                np.fill_diagonal(sims, -np.inf)
                floor = np.array([-np.inf if t is None or t != t else t for t in worst], dtype=np.float64)
                better = sims.astype(np.float32) > floor[:, None]
                for i in np.flatnonzero(better.any(axis=1)).tolist():
                    cols = np.flatnonzero(better[i])
                    owner.append(int(ids[i]))
                    near.append([{"sim": float(sims[i, c]), "id": int(ids[c])} for c in cols])
            if owner:  # an empty column of lists would pass for one of numbers
                yield pd.DataFrame({"id": owner, "near": near})

    gathered = brought.groupBy("id").agg(F.collect_list("to").alias("to"), F.collect_list("v").alias("v"), F.collect_list(F.coalesce("worst", F.lit(float("nan")))).alias("worst"))
    found = gathered.drop("id").mapInPandas(compare, f"id long, near {LIST}")
    return merge_lists(graph.unionByName(found), degree)


def build_graph(nodes: DataFrame, path: str, *, degree: int = DEGREE, settled: float = SETTLED) -> tuple[DataFrame, float]:
    """The neighbour graph and the common norm; every round is written to the shared folder. Lists only get better, so the rounds come to an end."""
    spark = nodes.sparkSession
    stats = nodes.agg(F.count("*").alias("n"), F.max(F.expr("sqrt(aggregate(v, 0D, (s, x) -> s + x * x))")).alias("top")).first()
    top = float(stats["top"] or 1.0)
    graph = keep(merge_lists(cell_graph(nodes, stats["n"], top, degree), degree), f"{path}/graph0")
    release(spark)
    turn = 0
    while True:
        turn += 1
        after = keep(descend(nodes, graph, top, degree), f"{path}/graph{turn}")
        old = graph.select("id", F.col("near.id").alias("was"))
        moved = after.join(old, "id", "left").agg(F.sum(F.size(F.array_except("near.id", F.coalesce("was", F.array().cast("array<long>"))))).alias("new"), F.sum(F.size("near")).alias("all")).first()
        drop(spark, f"{path}/graph{turn - 1}")
        release(spark)
        graph = after
        if (moved["new"] or 0) <= settled * (moved["all"] or 0):
            break
    return graph, top


def search(nodes: DataFrame, graph: DataFrame, starts: DataFrame, path: str, *, beam: int = BEAM) -> DataFrame:
    """(id, near) for the nodes in starts (id): greedy search from their own lists, by plain inner product, until the first twenty of every list stay as they are."""
    spark = nodes.sparkSession
    dot = "cast(aggregate(zip_with({0}, {1}, (x, y) -> x * y), 0D, (s, x) -> s + x) as float)"
    me = nodes.join(starts, "id", "left_semi").select(F.col("id").alias("q"), F.col("v").alias("qv"))

    def rated(pairs: DataFrame) -> DataFrame:
        both = pairs.join(nodes.select("id", "v"), "id").join(me, "q")
        return both.select("q", F.struct(F.expr(dot.format("qv", "v")).alias("sim"), "id").alias("c"))

    seeds = graph.withColumnRenamed("id", "q").join(me, "q", "left_semi").select("q", F.explode("near.id").alias("id"))
    best = f"slice(sort_array(array_distinct(collect_list(c)), false), 1, {beam})"
    state = rated(seeds).groupBy("q").agg(F.expr(best).alias("near")).withColumn("done", F.array().cast("array<long>"))
    state = keep(state, f"{path}/step0")
    step = 0
    while True:  # ends: every node that stands among the best is looked at once
        step += 1
        # the nearest nodes whose neighbours have not been looked at
        todo = state.withColumn("next", F.expr(f"slice(array_except(transform(slice(near, 1, {2 * EXPAND}), x -> x.id), done), 1, {EXPAND})"))
        ring = todo.select("q", F.explode("next").alias("node")).join(graph.select(F.col("id").alias("node"), F.slice(F.col("near.id"), 1, LOOK).alias("out")), "node")
        fresh = ring.select("q", F.explode("out").alias("id")).where("q <> id").distinct()
        known = state.select("q", F.explode("near.id").alias("id"))
        new = rated(fresh.join(known, ["q", "id"], "left_anti"))
        grown = todo.select("q", F.explode("near").alias("c")).unionByName(new).groupBy("q").agg(F.expr(best).alias("near"))
        moved = todo.select("q", F.array_union("done", "next").alias("done"), F.expr("transform(slice(near, 1, 20), x -> x.id)").alias("was"))
        state = keep(grown.join(moved, "q").select("q", "near", "done", F.expr("transform(slice(near, 1, 20), x -> x.id) <> was").alias("changed")), f"{path}/step{step}")
        drop(spark, f"{path}/step{step - 1}")
        release(spark)
        if not state.where("changed").limit(1).count():
            break
    return state.select(F.col("q").alias("id"), "near")


def nearest(vectors: DataFrame, *, k: int = 20, every: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", folder: str | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest of each row whose id is divisible by `every`, its own row left out.

    Score is the inner product in double precision; ties go to the smaller id. Repeated ids with
    the same vector count once; a repeated id with different vectors is refused by nobody and
    stands for each of them. Fewer than k others: all. No usable vector: no rows.
    """
    spark = vectors.sparkSession
    path = folder or workspace(spark, "neighbours")
    good = keep(usable(vectors, id_col, vec_col), f"{path}/usable")
    nodes = keep(nodes_of(good, k + 1), f"{path}/nodes")
    graph, _ = build_graph(nodes, path, degree=max(DEGREE, k + 4))
    asked = keep(good.where(f"vec_id % {every} = 0").select(F.col("vec_id").alias("query_id"), "v").distinct().join(nodes.select("v", "id"), "v").select("query_id", "id"), f"{path}/asked")
    found = search(nodes, graph, asked.select("id").distinct(), path, beam=max(BEAM, 2 * k))
    # a node's equals are candidates too: the node stands in its own list
    pairs = found.select("id", F.explode("near.id").alias("c")).unionByName(asked.select("id", F.col("id").alias("c"))).distinct()
    score = F.expr("aggregate(zip_with(qv, v, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    rated = pairs.join(nodes.select(F.col("id").alias("c"), "v", "members"), "c").join(nodes.select("id", F.col("v").alias("qv")), "id").select("id", "c", "members", score.alias("score"))
    few = rated.withColumn("r", F.row_number().over(Window.partitionBy("id").orderBy(F.desc("score"), "c"))).where(F.col("r") <= k + 1)
    rows = asked.join(few, "id").select("query_id", F.explode("members").alias("vec_id"), "score").where("vec_id <> query_id")
    ranked = rows.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op9(spark, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
