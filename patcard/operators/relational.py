"""Operators around the graph methods, each on the given tables, with SQL of its own as oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from patcard.functions.hashing import hash01, portable_key


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, right_at: str, value: str) -> DataFrame:
    """Each left row with the value of the last right row of its key at or before its time: one sort of both sides together, no range join."""
    both = left.select("*", F.lit(1).alias("__side"), F.col(at).alias("__at"), F.lit(None).cast(right.schema[value].dataType).alias("__v")).unionByName(right.select(key, F.lit(0).alias("__side"), F.col(right_at).alias("__at"), F.col(value).alias("__v")), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy("__at", "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last_value", F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__at", "__v")


def range_join(events: DataFrame, hours: int = 1) -> DataFrame:
    """Clicks and later purchases of one user within some hours: time is cut into slots of that length, so the join has an equality to be dealt by; neighbouring slots are looked at too."""
    slot = F.floor(F.unix_timestamp("ts") / (3600 * hours))
    c = events.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("t0"), F.explode(F.array(slot, slot + 1)).alias("slot"))
    p = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("t1"), slot.alias("slot"))
    return c.join(p, ["user_id", "slot"]).where(F.col("t1").between(F.col("t0"), F.col("t0") + F.expr(f"interval {hours} hours"))).select("user_id", "click", "purchase")


def operators() -> dict:
    """name: (query, SQL)."""
    o: dict = {}
    o["op_filter_project"] = (lambda s, d: _t(s, d, "orders").where("o_orderdate >= timestamp '1996-01-01' and o_orderpriority in ('1-URGENT', '2-HIGH')").select("o_orderkey", "o_custkey"), "select o_orderkey, o_custkey from orders where o_orderdate >= timestamp '1996-01-01' and o_orderpriority in ('1-URGENT', '2-HIGH')")
    o["op_equi_join"] = (lambda s, d: _t(s, d, "orders").join(_t(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n")), "select o_custkey, count(*) n from orders join lineitem on o_orderkey = l_orderkey group by 1")
    o["op_hash_join_hint"] = (lambda s, d: _t(s, d, "orders").join(_t(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "select c_mktsegment, count(*) n from orders join customer on o_custkey = c_custkey group by 1")
    o["op_broadcast_join"] = (lambda s, d: _t(s, d, "supplier").join(F.broadcast(_t(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), "select n_name, count(*) n from supplier join nation on s_nationkey = n_nationkey group by 1")
    o["op_semi_join"] = (lambda s, d: _t(s, d, "customer").join(_t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey)")
    o["op_anti_join"] = (lambda s, d: _t(s, d, "orders").join(_t(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"), "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")
    o["op_outer_join"] = (lambda s, d: _t(s, d, "documents").select("doc_id").join(_t(s, d, "labels"), "doc_id", "left").select("doc_id", "quality", "toxic"), "select d.doc_id, quality, toxic from documents d left join labels l on d.doc_id = l.doc_id")
    o["op_full_outer"] = (lambda s, d: _t(s, d, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("nc")).join(_t(s, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("ns")), "k", "full").select("k", F.coalesce("nc", F.lit(0)).alias("nc"), F.coalesce("ns", F.lit(0)).alias("ns")), "select coalesce(a.k, b.k) k, coalesce(nc, 0) nc, coalesce(ns, 0) ns from (select c_nationkey k, count(*) nc from customer group by 1) a full join (select s_nationkey k, count(*) ns from supplier group by 1) b on a.k = b.k")
    o["op_theta_join"] = (lambda s, d: _t(s, d, "nation").alias("a").join(_t(s, d, "nation").alias("b"), F.col("a.n_nationkey") < F.col("b.n_nationkey")).where("a.n_regionkey = b.n_regionkey").select(F.col("a.n_nationkey").alias("x"), F.col("b.n_nationkey").alias("y")), "select a.n_nationkey x, b.n_nationkey y from nation a join nation b on a.n_nationkey < b.n_nationkey and a.n_regionkey = b.n_regionkey")
    o["op_range_join"] = (lambda s, d: range_join(_t(s, d, "events")), "select a.user_id, a.event_id click, b.event_id purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts between a.ts and a.ts + interval 1 hour")
    o["op_as_of_join"] = (lambda s, d: as_of(_t(s, d, "events").where("event_type = 'purchase'").select("user_id", "event_id", "ts"), _t(s, d, "events").where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("click")), "user_id", "ts", "ts", "click").select("event_id", F.col("last_value").alias("click")), "select p.event_id, c.click from (select * from events where event_type = 'purchase') p asof left join (select user_id, ts, max(event_id) click from events where event_type = 'click' group by 1, 2) c on p.user_id = c.user_id and p.ts >= c.ts")
    o["op_explode"] = (lambda s, d: _t(s, d, "documents").select("doc_id", F.explode(F.split("source", "c")).alias("part")), "select doc_id, unnest(string_split(source, 'c')) part from documents")
    o["op_aggregate"] = (lambda s, d: _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("s"), F.round(F.avg("l_quantity"), 6).alias("m"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi")), "select l_returnflag, count(*) n, round(sum(l_quantity), 2) s, round(avg(l_quantity), 6) m, min(l_quantity) lo, max(l_quantity) hi from lineitem group by 1")
    o["op_collect_set"] = (lambda s, d: _t(s, d, "orders").groupBy("o_custkey").agg(F.concat_ws(",", F.array_sort(F.collect_set("o_orderstatus"))).alias("st")), "select o_custkey, array_to_string(list_sort(list(distinct o_orderstatus)), ',') st from orders group by 1")
    o["op_max_by"] = (lambda s, d: _t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top")), "select o_custkey, arg_max(o_orderkey, row(o_totalprice, o_orderkey)) top from orders group by 1")
    o["op_distinct"] = (lambda s, d: _t(s, d, "lineitem").select("l_suppkey", "l_partkey").distinct().groupBy("l_suppkey").agg(F.count("*").alias("n")), "select l_suppkey, count(distinct l_partkey) n from lineitem group by 1")
    o["op_rollup"] = (lambda s, d: _t(s, d, "customer").join(_t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n")), "select n_regionkey, c_mktsegment, count(*) n from customer join nation on c_nationkey = n_nationkey group by rollup (n_regionkey, c_mktsegment)")
    o["op_cube"] = (lambda s, d: _t(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "select o_orderstatus, o_orderpriority, count(*) n from orders group by cube (o_orderstatus, o_orderpriority)")
    o["op_pivot"] = (lambda s, d: _t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0), "select o_orderpriority, count(*) filter (where o_orderstatus = 'F') F, count(*) filter (where o_orderstatus = 'O') O, count(*) filter (where o_orderstatus = 'P') P from orders group by 1")
    o["op_unpivot"] = (lambda s, d: _t(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "name", "val"), "select doc_id, 'quality' as name, quality val from labels union all select doc_id, 'toxic', toxic from labels")
    o["op_percentile"] = (lambda s, d: _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", F.lit(0.25)), 4).alias("q1"), F.round(F.median("l_extendedprice"), 4).alias("q2")), "select l_returnflag, round(quantile_cont(l_extendedprice, 0.25), 4) q1, round(median(l_extendedprice), 4) q2 from lineitem group by 1")
    o["op_window_rank"] = (lambda s, d: _t(s, d, "orders").select("o_custkey", "o_orderkey", F.row_number().over(Window.partitionBy("o_custkey").orderBy(portable_key(F.lit(3), F.col("o_custkey"), F.col("o_orderkey")), "o_orderkey")).alias("r")).where("r <= 2"), "select * from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by md5(concat_ws('|', '3', cast(o_custkey as varchar), cast(o_orderkey as varchar))), o_orderkey) r from orders) where r <= 2")
    o["op_window_frame"] = (lambda s, d: _t(s, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("prev"), F.count("*").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)).alias("n")), "select o_orderkey, lag(o_orderkey) over w prev, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row) n from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
    o["op_top_k"] = (lambda s, d: _t(s, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").limit(20), "select l_partkey, count(*) n from lineitem group by 1 order by n desc, l_partkey limit 20")
    o["op_set_ops"] = (lambda s, d: _t(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(_t(s, d, "supplier").select(F.col("s_nationkey").alias("k"))).union(_t(s, d, "nation").select(F.col("n_nationkey").alias("k")).exceptAll(_t(s, d, "supplier").select(F.col("s_nationkey").alias("k")).distinct())), "(select c_nationkey k from customer intersect select s_nationkey from supplier) union all (select n_nationkey from nation except all select distinct s_nationkey from supplier)")
    o["op_arrays"] = (lambda s, d: _t(s, d, "lineitem").groupBy("l_suppkey").agg(F.collect_set("l_partkey").alias("p")).select("l_suppkey", F.size("p").alias("n"), F.size(F.filter("p", lambda x: x % 2 == 0)).alias("even"), F.array_max("p").alias("hi")), "select l_suppkey, len(p) n, len(list_filter(p, lambda x: x % 2 = 0)) even, list_max(p) hi from (select l_suppkey, list(distinct l_partkey) p from lineitem group by 1)")
    o["op_array_intersect"] = (lambda s, d: _intersect(s, d), "select a.l_suppkey x, b.l_suppkey y, count(*) n from (select distinct l_suppkey, l_partkey from lineitem where l_suppkey < 5) a join (select distinct l_suppkey, l_partkey from lineitem where l_suppkey < 5) b on a.l_partkey = b.l_partkey and a.l_suppkey < b.l_suppkey group by 1, 2")
    o["op_json"] = (lambda s, d: _t(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k")), "select event_id, cast(json_extract(props, '$.k') as int) k from events")
    o["op_strings"] = (lambda s, d: _t(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit("<p>"), F.lit(0))).alias("paras"), F.md5("url").alias("m"), F.lower(F.regexp_extract("url", "^(https?)", 1)).alias("scheme")), "select page_id, len(regexp_extract_all(html, '<p>')) paras, md5(url) m, lower(regexp_extract(url, '^(https?)', 1)) scheme from pages")
    o["op_dates"] = (lambda s, d: _t(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("m")).agg(F.count("*").alias("n")), "select cast(year(o_orderdate) as int) y, strftime(date_trunc('month', o_orderdate), '%Y-%m') m, count(*) n from orders group by 1, 2")
    o["op_math"] = (lambda s, d: _t(s, d, "part").select("p_partkey", F.ceil(F.col("p_size") / 7).alias("c"), F.pmod("p_partkey", F.lit(13)).alias("m"), F.round(F.log(F.col("p_retailprice") + 1), 6).alias("l"), F.greatest(F.col("p_size"), F.lit(10)).alias("g")), "select p_partkey, cast(ceil(p_size / 7) as bigint) c, p_partkey % 13 m, round(ln(p_retailprice + 1), 6) l, greatest(p_size, 10) g from part")
    o["op_vector"] = (lambda s, d: _t(s, d, "embeddings").select("vec_id", F.round(F.expr("aggregate(transform(embedding, x -> double(x) * double(x)), 0D, (a, b) -> a + b)"), 6).alias("norm2")), "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) norm2 from embeddings")
    o["op_hash_sample"] = (lambda s, d: _t(s, d, "orders").where(hash01(F.lit(5), F.col("o_orderkey")) < 0.1).select("o_orderkey"), "select o_orderkey from orders where ('0x' || substr(md5(concat_ws('|', '5', cast(o_orderkey as varchar))), 1, 15))::bigint / 1152921504606846976.0 < 0.1")
    o["op_correlated_subquery"] = (_sql("select c_custkey from {customer} c where c_acctbal > (select avg(c2.c_acctbal) from {customer} c2 where c2.c_nationkey = c.c_nationkey)"), "select c_custkey from customer c where c_acctbal > (select avg(c2.c_acctbal) from customer c2 where c2.c_nationkey = c.c_nationkey)")
    o["op_recursive"] = (_sql("with recursive r(conv_id, turn, n) as (select conv_id, turn, 1 from {conversations} where turn = 0 union all select c.conv_id, c.turn, r.n + 1 from r join {conversations} c on c.conv_id = r.conv_id and c.turn = r.turn + 1) select conv_id, max(n) as n from r group by conv_id"), "with recursive r as (select conv_id, turn, 1 n from conversations where turn = 0 union all select c.conv_id, c.turn, r.n + 1 from r join conversations c on c.conv_id = r.conv_id and c.turn = r.turn + 1) select conv_id, max(n) n from r group by conv_id")
    return o


def _sql(text: str):
    import re

    return lambda s, d: s.sql(re.sub(r"\{(\w+)\}", lambda m: f"parquet.`{d}/{m[1]}.parquet`", text))


def _intersect(s, d) -> DataFrame:
    """Adjacency as sorted arrays and their intersections inside the JVM."""
    a = _t(s, d, "lineitem").where("l_suppkey < 5").groupBy("l_suppkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("p"))
    b = a.select(F.col("l_suppkey").alias("y"), F.col("p").alias("p2"))
    return a.join(b, F.col("l_suppkey") < F.col("y")).select(F.col("l_suppkey").alias("x"), "y", F.size(F.array_intersect("p", "p2")).cast("long").alias("n")).where("n > 0")
