"""Every graph query by name, and the SQL of those that SQL can express."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patcard.baselines import sampling as S
from patcard.baselines import summaries as M
from patcard.functions import metrics
from patcard.functions.surface import canonical_code, ht_mean, register_functions, relation_stats, sorted_intersect
from patcard.functions.theory import agm_bound, edge_walk_chances, guarantee_check, ht_variance, sample_space, theoretical_calls, variance_bound, variance_curve, walked_space
from patcard.index import hard_patterns as I
from patcard.operators.relational import operators
from patcard.operators.walk import Walker, auto_ratio, choose_order, embeddings, exact_count, finish, progressive, sample_size, vertex_walk
from patcard.plans import oracle, planner, workloads
from patcard.plans import oracle_methods as O
from patcard.plans.query import parse_pattern
from patcard.sources.graphs import GRAPHS, PATTERNS, TOY_QUERY, from_csv, from_triples, toy
from patcard.sources.workspace import workspace
from patcard.streaming import events

#: Orders of the registered walks, so that their SQL can be written without looking at data.
ORDERS = {
    "P1": ("n", "c", "o", "p"), "P2": ("n", "s", "c", "o"), "P3": ("c", "o", "s", "p1", "p2"), "P4t": ("m", "s", "o", "c", "n", "p"), "P5": ("s", "o", "p"), "P6": ("n", "s", "c", "o"), "P7": ("n", "s", "c", "o", "p"),
    "P9": ("a", "b", "c"), "P10": ("a", "b", "c"), "P12": ("a", "b", "c", "d"), "P13": ("a", "b", "c"), "P14": ("a", "b", "c"), "P15": ("a", "b", "c", "d", "e"), "P16": ("k", "u"), "P18": ("s", "d"),
}
#: Two users of one item, for samples of any edges: rarer patterns are not met at all.
SHARED_ITEM = "(u1)-[click]->(k), (u2)-[purchase]->(k)"
CALLS = {"P15": 40, "P16": 20, "P18": 10, "P10": 30}


def _g(spark, sf_dir, pid):
    g = GRAPHS[PATTERNS[pid][0]](spark, sf_dir)
    return (g.kept() if g.name == "G_vec" else g), parse_pattern(PATTERNS[pid][1])


def _est(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if c in ("est", "bound", "space") else F.col(c) for c in cols or df.columns])


def flagship(spark, sf_dir):
    """Hybrid walk on the part-order-supplier triangle, with the truth and the q-error beside the estimate."""
    g, q = _g(spark, sf_dir, "P5")
    g = g.persist()
    ix = I.build_index(g, max_edges=1, zeta=0.9, calls=20, use_labels=workloads.KINDS, force=True)
    est = vertex_walk(g, q, calls=100, trials=3, index=ix)
    truth = exact_count(g, q).withColumnRenamed("cnt", "truth")
    return est.crossJoin(F.broadcast(truth)).withColumn("q_error", metrics.q_error(F.col("est"), F.col("truth")))


def queries() -> dict:
    out: dict = {}
    for name, load in GRAPHS.items():
        out[f"edges_{name}"] = lambda s, d, load=load: load(s, d).edges
        out[f"vertices_{name}"] = lambda s, d, load=load: load(s, d).labels
    for pid in PATTERNS:
        out[f"exact_{pid}"] = lambda s, d, pid=pid: exact_count(*_g(s, d, pid))
        out[f"stats_{pid}"] = lambda s, d, pid=pid: _stats(s, d, pid)
        out[f"order_{pid}"] = lambda s, d, pid=pid: _order(s, d, pid)
        out[f"agm_{pid}"] = lambda s, d, pid=pid: _agm(s, d, pid)
    for pid, order in ORDERS.items():
        out[f"vwalk_{pid}"] = lambda s, d, pid=pid, order=order: _est(vertex_walk(*_g(s, d, pid), calls=CALLS.get(pid, 4), trials=2, order=order))
    walk = lambda pid, **o: lambda s, d: _est(vertex_walk(*_g(s, d, pid), order=ORDERS[pid], **o))
    out["vwalk_nobranch_P6"] = walk("P6", calls=60, trials=2, k=None)
    out["vwalk_plain_P6"] = walk("P6", calls=20, trials=2, k=8, adaptive=False)
    out["vwalk_iso_P9"] = walk("P9", calls=4, trials=2, semantics="iso")
    out["vwalk_skip_P7"] = walk("P7", calls=4, skip=True)
    out["vwalk_replace_P6"] = walk("P6", calls=20, replace=True)
    out["vwalk_budget_P6"] = walk("P6", budget=100)
    out["vwalk_ratio_P6"] = walk("P6", ratio=0.001)
    out["samplesize_P6"] = lambda s, d: s.createDataFrame([(m, sample_size(*_g(s, d, "P6"), 0.001, m)) for m in ("union", "sum")], "n_mode string, s long")
    out["vwalk_b1_P5"] = walk("P5", calls=1, k=1, adaptive=False)
    out["vwalk_domain_P6"] = lambda s, d: _domain_walk(s, d)
    out["vwalk_disconnected"] = lambda s, d: _est(vertex_walk(GRAPHS["G_trade"](s, d), parse_pattern("(n)-[in_region]->(r), (c)-[cust_in]->(m)"), calls=10))
    out["embeddings_P10"] = lambda s, d: embeddings(*_g(s, d, "P10"))
    out["profile_P6"] = lambda s, d: Walker(*_g(s, d, "P6"), ORDERS["P6"]).profile(s, 1, 10)
    out["progressive_P5"] = lambda s, d: progressive(Walker(*_g(s, d, "P5"), ORDERS["P5"]).weights(s, 1, 20), 4, 20).select("trial", "round", F.round("est", 4).alias("est"), F.round("half", 4).alias("half"))
    out["autoratio_P6"] = lambda s, d: s.createDataFrame([auto_ratio(*_g(s, d, "P6"), target=0.3, start=20, cap=80)], "calls int, est double, half double")
    out["subqueries_P7"] = lambda s, d: _subqueries(s, d)
    out["joinorder_P7"] = lambda s, d: _join_order(s, d)
    # baselines
    out["htblind_toy"] = lambda s, d: _est(S.ht_blind(GRAPHS["G_act"](s, d), parse_pattern(SHARED_ITEM), calls=4000))
    out["htindep_P5"] = lambda s, d: _est(S.ht_independent(*_g(s, d, "P5"), calls=200))
    out["ewalk_P5"] = lambda s, d: _est(S.edge_walk(*_g(s, d, "P5"), calls=300, order=list(parse_pattern(PATTERNS["P5"][1]).edges)))
    out["ewalk_early_P6"] = lambda s, d: _est(S.edge_walk(*_g(s, d, "P6"), calls=300, check="early", order=list(parse_pattern(PATTERNS["P6"][1]).edges)))
    out["ewalk_tuned_P5"] = lambda s, d: S.tuned_edge_walk(*_g(s, d, "P5"), calls=50, pilot=10)
    out["ewalk_domain_P6"] = lambda s, d: _edge_domains(s, d)
    out["batchwalk_P5"] = lambda s, d: _est(S.batched_edge_walk(*_g(s, d, "P5"), batch=1000, trials=2, order=list(parse_pattern(PATTERNS["P5"][1]).edges)))
    out["treebound_P4t"] = lambda s, d: S.tree_bound(*_g(s, d, "P4t"))
    out["treewalk_P5"] = lambda s, d: S.tree_bound_walk(*_g(s, d, "P5"), calls=50)
    out["corrhash_P5"] = lambda s, d: _est(S.correlated_sampling(*_g(s, d, "P5"), p=0.5, trials=2))
    out["graphlet_P5"] = lambda s, d: S.graphlet_walk(*_g(s, d, "P5"), calls=100)
    out["charset_P3"] = lambda s, d: _est(M.charset_estimate(M.charset_build(_g(s, d, "P3")[0]), *_g(s, d, "P3")))
    out["summary_P6"] = lambda s, d: _est(M.summary_estimate(M.summary_build(_g(s, d, "P6")[0], 8), _g(s, d, "P6")[1]))
    out["boundsketch_P5"] = lambda s, d: _est(M.bound_sketch_estimate(M.bound_sketch(*_g(s, d, "P5"), 4), _g(s, d, "P5")[1]))
    out["catalogue_P5"] = lambda s, d: _est(M.catalogue_estimate(*_g(s, d, "P5")))
    out["cyclebranch_P6"] = lambda s, d: S.cycle_branch_walk(*_g(s, d, "P6"), calls=10)
    out["indep_P5"] = lambda s, d: _est(M.independence_estimate(*_g(s, d, "P5")))
    out["fpm_G_trade"] = lambda s, d: I.frequent_patterns(GRAPHS["G_trade"](s, d).persist(), 1, 10, workloads.KINDS)
    # index
    out["domain_tree_P4t"] = lambda s, d: _domain_rows(I.domains_tree(*_g(s, d, "P4t")))
    out["domain_exact_P5"] = lambda s, d: _domain_rows(I.domains_exact(*_g(s, d, "P5")))
    out["domain_superset_P6"] = lambda s, d: _domain_rows(I.domains_superset(*_g(s, d, "P6"), rounds=1)).groupBy("u").count()
    out["index_level1"] = lambda s, d: I.build_index(GRAPHS["G_trade"](s, d).persist(), max_edges=1, use_labels=workloads.KINDS, force=True).table()
    out["index_patterns"] = lambda s, d: workloads.small_index(GRAPHS["G_trade"](s, d).persist()).table()
    out["hybrid_P6"] = lambda s, d: _hybrid(s, d)
    out["refresh_G_act"] = lambda s, d: workloads.stale_index(s, d).refresh(workloads.stale_activity(s, d, 1.0).persist()).table()
    out["labelgroups_G_copart"] = lambda s, d: I.group_labels(GRAPHS["G_copart"](s, d), 8)
    out["index_report"] = lambda s, d: s.createDataFrame([(k, float(v)) for k, v in I.build_index(GRAPHS["G_act"](s, d).persist(), max_edges=1, calls=50, force=True).report().items()], "measure string, value double")
    out["index_saved"] = lambda s, d: _saved(s, d)
    out["index_groups"] = lambda s, d: I.build_index(GRAPHS["G_doc"](s, d).persist(), max_edges=1, use_labels=["doc", "source", "en", "de", "fr", "es"], groups=2, force=True).table().select("code", "n_edges", "size")
    out["exact_index_P16"] = lambda s, d: _exact_index(s, d)
    # measures over a table of estimates: part-order-supplier triangles by two methods
    out["qerror_P5"] = lambda s, d: _runs(s, d).select("method", "trial", F.round(metrics.q_error(F.col("est"), F.col("truth")), 6).alias("q"))
    out["box_stats"] = lambda s, d: metrics.box_stats(_runs(s, d), "method").select("method", *[F.round(c, 6).alias(c) for c in ("q1", "median", "q3", "low", "high")])
    out["zero_rate"] = lambda s, d: metrics.zero_rate(_runs(s, d), "method")
    out["bias_test"] = lambda s, d: metrics.bias_test(_runs(s, d).where("method = 'vertex'").select("trial", "est"), float(exact_count(*_g(s, d, "P5")).first()["cnt"])).select(*[F.round(c, 4).alias(c) for c in ("mean", "se", "z")])
    out["variance_curve"] = lambda s, d: variance_curve(Walker(*_g(s, d, "P5"), ORDERS["P5"]).weights(s, 1, 32), (1, 2, 4)).select("size", F.round("variance", 2).alias("variance"))
    out["htvariance_P10"] = lambda s, d: ht_variance(edge_walk_chances(*_g(s, d, "P10"), list(parse_pattern(PATTERNS["P10"][1]).edges))).select("m", F.round("variance", 2).alias("variance"))
    out["walkedspace_toy"] = lambda s, d: _walked(s)
    # surface
    out["op_views"] = lambda s, d: relation_stats(s, GRAPHS["G_trade"](s, d))
    out["op_pandas_udf"] = lambda s, d: _codes(s, d)
    out["op_udaf"] = lambda s, d: s.read.parquet(f"{d}/orders.parquet").groupBy("o_orderpriority").agg(ht_mean("o_totalprice").alias("m")).select("o_orderpriority", F.round(F.col("m")[0], 4).alias("est"), F.round(F.col("m")[1], 4).alias("half"))
    out["op_udtf"] = lambda s, d: _table_function(s, d)
    out["op_sorted_intersect"] = lambda s, d: _sorted_intersect(s, d)
    out["op_sample"] = lambda s, d: s.read.parquet(f"{d}/orders.parquet").sampleBy("o_orderstatus", {"F": 1.0, "O": 1.0, "P": 0.0}, 1).sample(1.0, 2).groupBy("o_orderstatus").agg(F.count("*").alias("n"))
    out["op_map"] = lambda s, d: s.read.parquet(f"{d}/orders.parquet").groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m")).select("o_custkey", F.size(F.map_keys("m")).alias("kinds"), F.coalesce(F.col("m")["F"], F.lit(0)).alias("f"))
    out["op_sketch"] = lambda s, d: s.read.parquet(f"{d}/lineitem.parquet").agg((F.abs(F.approx_count_distinct("l_partkey", 0.01) / F.count_distinct("l_partkey") - 1) < 0.05).alias("near"))
    out["source_csv"] = lambda s, d: _round_trip(s, d, "csv")
    out["source_triples"] = lambda s, d: _round_trip(s, d, "triples")
    out["sink_stored"] = lambda s, d: GRAPHS["G_act"](s, d).store(workspace(s, "stored")).edges
    # theory
    out["varbound"] = lambda s, d: exact_count(*_g(s, d, "P16")).select(F.round(F.lit(variance_bound(1 / 32, 2, 1.0)) * F.col("cnt") * F.col("cnt"), 3).alias("bound"), F.lit(theoretical_calls(1 / 32, 2, 0.5, 0.9)).cast("long").alias("calls"))
    out["coverage_toy"] = lambda s, d: guarantee_check(vertex_walk(*_g(s, d, "P16"), calls=40, trials=10, k=2, adaptive=False, order=ORDERS["P16"]), float(exact_count(*_g(s, d, "P16")).first()["cnt"]), 0.5)
    out["samplespace_toy"] = lambda s, d: _spaces(s, d)
    out |= workloads.WORKLOADS
    out |= {n: f for n, (f, _) in operators().items()}
    out |= {n: f for n, (f, _) in events.queries().items()}
    return out


def _runs(s, d) -> DataFrame:
    """(method, trial, est, truth): three trials of two methods on P5."""
    g, q = _g(s, d, "P5")
    truth = exact_count(g, q).select(F.col("cnt").cast("double").alias("truth"))
    runs = vertex_walk(g, q, calls=4, trials=3, order=ORDERS["P5"]).select(F.lit("vertex").alias("method"), "trial", "est")
    runs = runs.unionByName(S.edge_walk(g, q, calls=20, trials=3, order=list(q.edges)).select(F.lit("edge").alias("method"), "trial", "est"))
    return runs.crossJoin(F.broadcast(truth))


def _saved(s, d):
    """Entries of an index that was saved and loaded, with the rows that its domain files hold."""
    g = GRAPHS["G_act"](s, d).persist()
    ix = I.build_index(g, max_edges=1, force=True)
    again = I.load_index(g, ix.save(workspace(s, "saved")))
    return again.domain_rows().groupBy("code", "u").agg(F.count("*").alias("n"))


def _exact_index(s, d):
    g, q = _g(s, d, "P16")
    g = g.persist()
    return exact_count(g, q, index=I.build_index(g, max_edges=2, force=True))


def _walked(s):
    q, rows = parse_pattern(TOY_QUERY), None
    for which in (1, 2):
        g = toy(s, which)
        for method, order in (("edge", q.edges), ("vertex", ("u1", "u2", "u4", "u3", "u5"))):
            one = walked_space(g, q, method, order).select(F.lit(which).alias("toy"), F.lit(method).alias("method"), "space")
            rows = one if rows is None else rows.unionByName(one)
    return rows


def _codes(s, d):
    """The star of the kinds of events that a user has, as a pattern: each that occurs, with its code and its number of users."""
    kinds = s.read.parquet(f"{d}/events.parquet").groupBy("user_id").agg(F.array_sort(F.collect_set("event_type")).alias("k"))
    star = F.array_join(F.transform("k", lambda x, i: F.concat(F.lit("(u)-["), x, F.lit("]->(x"), i.cast("string"), F.lit(")"))), ", ")
    return kinds.where(F.size("k") > 0).groupBy(star.alias("pattern")).agg(F.count("*").alias("users")).select("pattern", canonical_code("pattern").alias("code"), "users")


def _table_function(s, d):
    """Pairs of customers of a nation, one small graph for each nation and segment."""
    register_functions(s)
    lines = F.array_join(F.array_sort(F.collect_list(F.concat_ws(" ", F.lit(0) - 1 - F.col("c_custkey"), F.lit("in"), F.col("c_nationkey")))), "\n")
    graphs = s.read.parquet(f"{d}/customer.parquet").where("c_custkey is not null and c_nationkey is not null").groupBy("c_nationkey", "c_mktsegment").agg(lines.alias("edges"))
    walks = s.sql("select c_nationkey, c_mktsegment, w from {g} g, lateral estimate_pattern('(a)-[in]->(n), (b)-[in]->(n)', g.edges, 5, 1)", g=graphs)
    return walks.groupBy("c_nationkey", "c_mktsegment").agg(F.round(F.avg("w"), 6).alias("est"), F.count("*").alias("n"))


def _sorted_intersect(s, d):
    a = s.read.parquet(f"{d}/lineitem.parquet").where("l_suppkey < 5").groupBy("l_suppkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("p"))
    b = a.select(F.col("l_suppkey").alias("y"), F.col("p").alias("p2"))
    return a.join(b, F.col("l_suppkey") < F.col("y")).select(F.col("l_suppkey").alias("x"), "y", F.size(sorted_intersect("p", "p2")).cast("long").alias("n")).where("n > 0")


def _round_trip(s, d, kind):
    """The activity graph's edges, written as text and read back."""
    g, path = GRAPHS["G_act"](s, d), workspace(s, kind)
    if kind == "csv":
        g.edges.write.option("header", True).csv(path)
        return from_csv(s, path, g.labels).edges
    g.edges.select(F.concat_ws("\t", "src", "elabel", "dst")).write.text(path)
    return from_triples(s, path, g.labels).edges


def _stats(s, d, pid):
    g, q = _g(s, d, pid)
    return s.createDataFrame([(r["eid"], r["n"], r["na"], r["nb"]) for r in g.stats(q)], "eid int, n long, na long, nb long")


def _spaces(s, d):
    g, q = _g(s, d, "P16")
    st, edges = g.stats(q), g.edges.count()
    return s.createDataFrame([(m, sample_space(st, edges, m)) for m in ("blind", "labelled")], "method string, space double")


def _order(s, d, pid):
    g, q = _g(s, d, pid)
    return s.createDataFrame(list(enumerate(choose_order(q, g.stats(q)), 1)), "position int, u string")


def _agm(s, d, pid):
    g, q = _g(s, d, pid)
    bound, _ = agm_bound(q, g.stats(q))
    return s.createDataFrame([(round(math.log(bound), 9) if bound else 0.0, bound == 0)], "log_bound double, is_empty boolean")


def _domain_rows(domains) -> DataFrame:
    out = None
    for u, df in domains.items():
        one = df.select(F.lit(u).alias("u"), "v")
        out = one if out is None else out.unionByName(one)
    return out


def _domain_walk(s, d):
    g, q = _g(s, d, "P6")
    dom = I.domains_tree(g, parse_pattern("(c)-[placed]->(o)-[shipped_by]->(s)"))
    return _est(finish(Walker(g, q, ORDERS["P6"], domains={"s": dom["s"]}).weights(s, 2, 10)))


def _hybrid(s, d):
    g = GRAPHS["G_trade"](s, d).persist()
    return vertex_walk(g, parse_pattern(PATTERNS["P6"][1]), calls=20, trials=2, index=workloads.small_index(g))


def _edge_domains(s, d):
    g = GRAPHS["G_trade"](s, d).persist()
    return S.edge_walk(g, parse_pattern(PATTERNS["P6"][1]), calls=50, index=workloads.small_index(g))


def _subqueries(s, d):
    """All parts walk over the same relations, so these are held in memory."""
    g, q = _g(s, d, "P7")
    return planner.estimate_subqueries(g.persist(), q)


def _join_order(s, d):
    g, q = _g(s, d, "P7")
    g = g.persist()
    sizes = {r["part"]: r["est"] for r in planner.estimate_subqueries(g, q).collect()}
    order, cost = planner.best_join_order(g, q, sizes)
    return s.createDataFrame([(",".join(order), float(cost))], "order_ string, cost double")


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for name in GRAPHS:
        out[f"edges_{name}"] = f"with {oracle.GRAPH_SQL[name]} select src, elabel, dst from e"
        out[f"vertices_{name}"] = f"with {oracle.GRAPH_SQL[name]} select v, label from vl"
    for pid in PATTERNS:
        out[f"exact_{pid}"] = oracle.exact_sql(pid)
        out[f"stats_{pid}"] = oracle.stats_sql(pid)
    for pid, order in ORDERS.items():
        out[f"vwalk_{pid}"] = oracle.walk_sql(pid, order, calls=CALLS.get(pid, 4), trials=2)
    out["vwalk_nobranch_P6"] = oracle.walk_sql("P6", ORDERS["P6"], calls=60, trials=2, k=None)
    out["vwalk_plain_P6"] = oracle.walk_sql("P6", ORDERS["P6"], calls=20, trials=2, k=8, adaptive=False)
    out["vwalk_iso_P9"] = oracle.walk_sql("P9", ORDERS["P9"], calls=4, trials=2, semantics="iso")
    out["vwalk_b1_P5"] = oracle.walk_sql("P5", ORDERS["P5"], calls=1, trials=1, k=1, adaptive=False)
    out["vwalk_domain_P6"] = oracle.walk_sql("P6", ORDERS["P6"], calls=10, trials=2, domains={"s": "dom_s"}, extra=", dom_s as (select distinct x.dst v from e x join e y on x.src = y.dst and y.elabel = 'placed' where x.elabel = 'shipped_by')")
    out["embeddings_P10"] = oracle.embeddings_sql("P10")
    for pid in PATTERNS:
        out[f"order_{pid}"], out[f"agm_{pid}"] = O.order_sql(pid), O.agm_sql(pid)
    out |= O.measure_sql(oracle_edge_walk("P5", 20, "end", trials=3), ORDERS["P5"])
    out["htblind_toy"] = O.independent_sql(oracle.GRAPH_SQL["G_act"], parse_pattern(SHARED_ITEM), calls=4000, blind=True)
    act_walk = oracle.walk_on(oracle.GRAPH_SQL["G_act"], parse_pattern(PATTERNS["P16"][1]), ORDERS["P16"], calls=40, trials=10, k=2, adaptive=False, columns="avg(w) est")
    out["coverage_toy"] = f"select avg((abs(est - cnt) < 0.5 * cnt)::int::double) coverage from ({act_walk}), ({oracle.exact_sql('P16')})"
    out["walkedspace_toy"] = O.walked_sql()
    out["samplesize_P6"] = O.sample_size_sql("P6", 0.001)
    out["vwalk_disconnected"] = O.product_sql("G_trade", [("(c)-[cust_in]->(m)", ("m", "c"), 0), ("(n)-[in_region]->(r)", ("r", "n"), 7919)], calls=10)
    out["htvariance_P10"] = O.chances_sql("P10")
    out["exact_index_P16"] = oracle.exact_sql("P16")
    out["index_saved"] = f"with {oracle.GRAPH_SQL['G_act']} select ';#1d0:' || elabel code, 'x1' u, count(distinct dst) n from e group by elabel union all select ';#1d0:' || elabel, 'x0', count(distinct src) from e group by elabel"
    out["index_level1"] = f"with {oracle.GRAPH_SQL['G_trade']}, k as (select v, label from vl where label in ({', '.join(repr(x) for x in workloads.KINDS)})) select case when a.label <= b.label then a.label || ';' || b.label || '#0d1:' else b.label || ';' || a.label || '#1d0:' end || elabel code, 1 n_edges, true hard, 1.0::double fail_rate, count(distinct src) + count(distinct dst) as size from e join k a on a.v = src join k b on b.v = dst group by elabel, a.label, b.label"
    out["fpm_G_trade"] = f"with {oracle.GRAPH_SQL['G_trade']}, k as (select v, label from vl where label in ({', '.join(repr(x) for x in workloads.KINDS)})) select case when a.label <= b.label then a.label || ';' || b.label || '#0d1:' else b.label || ';' || a.label || '#1d0:' end || elabel code, 1 n_edges, least(count(distinct src), count(distinct dst)) support from e join k a on a.v = src join k b on b.v = dst group by elabel, a.label, b.label having support >= 10"
    out["op_views"] = f"with {oracle.GRAPH_SQL['G_trade']} select elabel, count(*) n_edges, count(distinct src) n_src, count(distinct dst) n_dst, (select max(n) from (select count(*) n from e x where x.elabel = e.elabel group by x.src)) max_deg_src, (select max(n) from (select count(*) n from e x where x.elabel = e.elabel group by x.dst)) max_deg_dst from e group by elabel"
    out["op_udaf"] = "select o_orderpriority, round(avg(o_totalprice), 4) est, round(1.96 * stddev_samp(o_totalprice) / sqrt(count(*)), 4) half from orders group by 1"
    out["op_udtf"] = "select c_nationkey, c_mktsegment, (count(distinct c_custkey) * count(distinct c_custkey))::double est, 5::bigint n from customer where c_custkey is not null and c_nationkey is not null group by 1, 2"
    out["op_sorted_intersect"] = operators()["op_array_intersect"][1]
    out["op_sample"] = "select o_orderstatus, count(*) n from orders where o_orderstatus <> 'P' group by 1"
    out["op_map"] = "select o_custkey, count(distinct o_orderstatus)::int kinds, count(*) filter (o_orderstatus = 'F') f from orders group by 1"
    out["op_sketch"] = "select true as near"
    for name in ("source_csv", "source_triples", "sink_stored"):
        out[name] = out["edges_G_act"]
    out["profile_P6"] = O.profile_sql("P6", ORDERS["P6"], calls=10)
    out["progressive_P5"] = O.progressive_sql("P5", ORDERS["P5"], rounds=4, calls=20)
    out["vwalk_budget_P6"] = O.budget_sql("P6", ORDERS["P6"], budget=100)
    out["vwalk_skip_P7"] = oracle.walk_sql("P7", ORDERS["P7"], calls=4, trials=1)
    out["htindep_P5"] = O.independent_sql(oracle.GRAPH_SQL["G_trade"], parse_pattern(PATTERNS["P5"][1]), calls=200, blind=False)
    out["batchwalk_P5"] = O.batch_sql("P5", parse_pattern(PATTERNS["P5"][1]).edges, batch=1000, trials=2)
    out["corrhash_P5"] = O.correlated_sql("P5", p=0.5, trials=2)
    out["charset_P3"] = O.charset_sql("P3", M.stars_of(parse_pattern(PATTERNS["P3"][1])))
    out["summary_P6"] = O.summary_sql("P6", 8)
    out["boundsketch_P5"] = O.bound_sketch_sql("P5", 4)
    out["catalogue_P5"] = O.catalogue_triangle_sql("P5", M.chain_order(parse_pattern(PATTERNS["P5"][1])))
    out["indep_P5"] = O.independence_sql("P5")
    out["domain_superset_P6"] = O.superset_sql("P6")
    out["labelgroups_G_copart"] = O.label_groups_sql("G_copart", 8)
    out["varbound"] = f"select round(1.0 / 32 / (1 - 1.0 / 32) * (pow(32, 2) - 1) * cnt::double * cnt::double, 3) bound, ceil(round(1.0 / 32 / (1 - 1.0 / 32) * (pow(32, 2) - 1) / (0.25 * 0.1), 3))::bigint calls from ({oracle.exact_sql('P16')})"
    out["samplespace_toy"] = f"with {oracle.GRAPH_SQL['G_act']} select 'blind' as method, pow(count(*), 2)::double as space from e union all select 'labelled', count(*) filter (elabel = 'click')::double * count(*) filter (elabel = 'purchase') from e"
    out["domain_tree_P4t"] = _domain_sql("P4t")
    out["domain_exact_P5"] = _domain_sql("P5")
    out["treebound_P4t"] = oracle.exact_sql("P4t").replace("cast(count(*) as bigint) cnt", "cast(count(*) as double) bound")
    out["ewalk_P5"] = oracle_edge_walk("P5", 300, "end")
    out["ewalk_early_P6"] = oracle_edge_walk("P6", 300, "early")
    out |= {n: sql for n, (_, sql) in operators().items() if sql}
    out |= {n: sql for n, (_, sql) in events.queries().items() if sql}
    return out


def _domain_sql(pid: str) -> str:
    name, text = PATTERNS[pid]
    q = parse_pattern(text)
    return f"with {oracle.GRAPH_SQL[name]}, m as materialized (select * from {oracle._joined(q)}) " + " union all ".join(f"select distinct '{u}' u, {u} v from m" for u in q.names)


def oracle_edge_walk(pid: str, calls: int, check: str, seed: int = 0, trials: int = 1) -> str:
    """An edge walk in windows: a number for each pair of the first relation, then the least hash among the neighbours."""
    name, text = PATTERNS[pid]
    q = parse_pattern(text)
    first, *rest = q.edges
    num, text_of = oracle.bits, oracle.text
    ctes = [
        f"b as (select a, b, {num("'a'", text_of('a'), text_of('b'))} % {oracle.BUCKETS} bk from {oracle.relation(q, first)})",
        "pool as (select a, b, row_number() over (order by bk, a, b) - 1 idx, count(*) over () m from b)",
        f"l0 as (select t.range trial, c.range call from range({trials}) t, range({calls}) c)",
        f"s1 as (select l0.trial, l0.call, pool.m::double f__, pool.a {first.u}, pool.b {first.w} from l0 join pool on pool.idx = {num(f"'{seed}'", text_of('trial'), text_of('call'), "'0'")} % pool.m)",
    ]
    placed, last, copies = [first.u, first.w], "s1", []
    for i, e in enumerate(rest, 1):
        closes = e.u in placed and e.w in placed
        cols = ", ".join(["p.trial", "p.call", *[f"p.{v}" for v in placed], *[f"p.{c}" for _, c in copies]])
        if closes and check == "early":
            ctes.append(f"s{i + 1} as (select p.* from {last} p where exists (select 1 from {oracle.relation(q, e)} x where x.a = p.{e.u} and x.b = p.{e.w}))")
        else:
            near = e.u if e.u in placed else e.w
            far = e.other(near)
            cn, cf = ("a", "b") if near == e.u else ("b", "a")
            target = f"copy{i}" if closes else far
            key = ", ".join([f"'{seed}'", text_of("p.trial"), text_of("p.call"), f"'{i}'", text_of(f"p.{near}"), text_of(f"x.{cf}")])
            ctes.append(f"s{i + 1} as (select * exclude (n__, r__, f__), f__ * n__ f__ from (select {cols}, p.f__, x.{cf} {target}, count(*) over (partition by p.trial, p.call) n__, row_number() over (partition by p.trial, p.call order by md5(concat_ws('|', {key})), x.{cf}) r__ from {last} p join {oracle.relation(q, e)} x on x.{cn} = p.{near}) where r__ = 1)")
            (copies.append((far, target)) if closes else placed.append(far))
        last = f"s{i + 1}"
    ok = " and ".join(["true", *[f"{last}.{v} = {last}.{c}" for v, c in copies]])
    return f"with {oracle.GRAPH_SQL[name]}, {', '.join(ctes)}, w as (select l0.trial, l0.call, coalesce(sum({last}.f__), 0) w from l0 left join {last} on l0.trial = {last}.trial and l0.call = {last}.call and {ok} group by all) select trial, round(avg(w), 6) est, count(*) n_calls, cast(count(*) filter (w = 0) as bigint) n_failed from w group by trial"

