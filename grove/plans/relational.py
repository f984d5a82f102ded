"""Relational operators on forests: one query for each, with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from grove.functions import coins, udfs
from grove.operators.graph import degrees
from grove.session import cut, table
from grove.sources import forests as fs
from grove.sources import io


def leaves_and_hubs(s: SparkSession, d: str) -> DataFrame:
    """All leaves and hubs, chosen by degree alone."""
    deg = degrees(fs.forest_of(fs.brand_stars(s, d)))
    leaf, small, large = F.col("degree").isin(0, 1), F.col("degree").between(5, 99), F.col("degree") >= 100
    return deg.where(leaf | small | large).select("v", "degree", leaf.alias("leaf"))


def edge_attributes(s: SparkSession, d: str) -> DataFrame:
    o, c = table(s, d, "orders"), table(s, d, "customer")
    return o.join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n_orders"), F.countDistinct("c_custkey").alias("n_customers"))


def outer_differences(s: SparkSession, d: str) -> DataFrame:
    c = table(s, d, "customer").select(F.col("c_custkey").alias("k"))
    o = table(s, d, "orders").select(F.col("o_custkey").alias("k")).distinct().withColumn("has", F.lit(1))
    j = c.withColumn("is", F.lit(1)).join(o, "k", "full")
    return j.groupBy(F.col("is").isNotNull().alias("is_customer"), F.col("has").isNotNull().alias("has_orders")).agg(F.count("*").alias("n"))


def left_right_joins(s: SparkSession, d: str) -> DataFrame:
    n, su = table(s, d, "nation"), table(s, d, "supplier")
    left = n.join(su, n.n_nationkey == su.s_nationkey, "left").groupBy("n_nationkey").agg(F.count("s_suppkey").alias("n_left"))
    right = su.join(n, n.n_nationkey == su.s_nationkey, "right").groupBy(F.col("n_nationkey").alias("k")).agg(F.count("s_suppkey").alias("n_right"))
    return left.join(right, F.col("n_nationkey").eqNullSafe(F.col("k"))).select("n_nationkey", "n_left", "n_right")


def semi_anti(s: SparkSession, d: str) -> DataFrame:
    o = table(s, d, "orders").select("o_orderkey")
    li = table(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"))
    return o.join(li, "o_orderkey", "left_semi").agg(F.count("*").alias("with_lines")).crossJoin(o.join(li, "o_orderkey", "left_anti").agg(F.count("*").alias("without_lines")))


def degree_dominance(s: SparkSession, d: str) -> DataFrame:
    """Theta join on a bounded set: the 20 largest hubs."""
    hubs = degrees(fs.forest_of(fs.recursive_tree(s, d))).orderBy(F.desc("degree"), "v").limit(20)
    a, b = hubs.withColumnsRenamed({"v": "a", "degree": "da"}), hubs.withColumnsRenamed({"v": "b", "degree": "db"})
    return a.join(b, F.col("da") > F.col("db")).groupBy("a").agg(F.count("*").alias("dominates"))


def range_join(s: SparkSession, d: str) -> DataFrame:
    """Events within 2 hours after an earlier event of their user: equality on an hour bucket, then the range."""
    e = table(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    span = 2 * 3600 * 1_000_000
    a = e.withColumn("b", F.explode(F.array(F.floor(F.col("us") / span), F.floor(F.col("us") / span) + 1)))
    z = e.select(F.col("event_id").alias("later"), F.col("user_id").alias("u"), F.col("us").alias("us2"), F.floor(F.col("us") / span).alias("b2"))
    j = a.join(z, (F.col("user_id") == F.col("u")) & (F.col("b") == F.col("b2")) & (F.col("us2") > F.col("us")) & (F.col("us2") <= F.col("us") + span))
    return j.groupBy("user_id").agg(F.count("*").alias("pairs"))


def as_of_join(s: SparkSession, d: str) -> DataFrame:
    """Each purchase with the latest earlier click of its user: union and last value, one shuffle."""
    e = table(s, d, "events").where("event_type in ('click', 'purchase')")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click", last).where("event_type = 'purchase'").select("event_id", "user_id", "click")


def degree_histogram_f5(s: SparkSession, d: str) -> DataFrame:
    return degrees(fs.forest_of(fs.recursive_tree(s, d))).groupBy("degree").agg(F.count("*").alias("n"))


def percentiles(s: SparkSession, d: str) -> DataFrame:
    deg = degrees(fs.forest_of(fs.event_chains(s, d)))
    return deg.agg(F.expr("percentile(degree, 0.5)").cast("double").alias("median"), F.countDistinct("degree").alias("kinds"), F.max("degree").cast("long").alias("top"))


def revenue_rollup(s: SparkSession, d: str) -> DataFrame:
    o, c, n, r = (table(s, d, t) for t in ("orders", "customer", "nation", "region"))
    j = o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return j.rollup("r_name", "n_name").agg(F.count("*").alias("orders"), F.round(F.sum(F.col("o_totalprice").cast("decimal(18,2)")), 2).cast("double").alias("revenue"))


def revenue_cube(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def grouping_sets(s: SparkSession, d: str) -> DataFrame:
    table(s, d, "events").createOrReplaceTempView("grove_events")
    return s.sql("select event_type, user_id % 5 as part, count(*) as n from grove_events group by grouping sets ((event_type), (user_id % 5), ())")


def status_pivot(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").withColumn("part", F.col("user_id") % 3)
    return e.groupBy("part").pivot("event_type", ["click", "error", "purchase", "signup", "view"]).agg(F.count("event_id")).na.fill(0)


def windows(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events")
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select(
        "event_id", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("quarter"), F.lead("event_id").over(w).alias("next_id"),
        F.first("event_id").over(w).alias("first_id"), F.sum(F.lit(1)).over(w.rowsBetween(-2, 0)).alias("last3"),
        F.rank().over(W.partitionBy("event_type").orderBy("user_id")).alias("rnk"), F.dense_rank().over(W.partitionBy("event_type").orderBy("user_id")).alias("drnk"),
    )


def range_window(s: SparkSession, d: str) -> DataFrame:
    """Events of the same user in the hour up to each: a range frame on seconds."""
    e = table(s, d, "events").withColumn("sec", F.unix_seconds(F.col("ts").cast("timestamp")))
    w = W.partitionBy("user_id").orderBy("sec").rangeBetween(-3600, 0)
    return e.select("event_id", F.count("*").over(w).alias("in_hour"))


def top_hubs(s: SparkSession, d: str) -> DataFrame:
    return degrees(fs.forest_of(fs.hub_tree(s, d))).orderBy(F.desc("degree"), "v").limit(10)


def top_per_component(s: SparkSession, d: str) -> DataFrame:
    p = table(s, d, "part").select("p_brand", "p_partkey", "p_retailprice")
    r = F.row_number().over(W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))
    return p.withColumn("r", r).where("r <= 3").select("p_brand", "p_partkey", "r")


def set_operations(s: SparkSession, d: str) -> DataFrame:
    a = table(s, d, "orders").select((F.col("o_custkey") % 50).alias("k"))
    b = table(s, d, "customer").select((F.col("c_nationkey") * 3).cast("long").alias("k"))
    parts = {"union": a.union(b).distinct(), "union_all": a.unionByName(b), "intersect": a.intersect(b), "except": a.exceptAll(b), "minus": b.subtract(a)}
    out = None
    for name, df in parts.items():
        one = df.agg(F.count("*").alias("n"), F.sum("k").alias("total")).select(F.lit(name).alias("op"), "n", "total")
        out = one if out is None else out.unionByName(one)
    return out


def subqueries(s: SparkSession, d: str) -> DataFrame:
    table(s, d, "orders").createOrReplaceTempView("grove_orders")
    table(s, d, "customer").createOrReplaceTempView("grove_customer")
    return s.sql(
        "select c_custkey from grove_customer c where exists (select 1 from grove_orders o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'F') "
        "and (select count(*) from grove_orders o where o.o_custkey = c.c_custkey) > (select count(*) / (select count(*) from grove_customer) from grove_orders)"
    )


def recursive_cte(s: SparkSession, d: str) -> DataFrame:
    """Depths by Spark's own recursion: for shallow trees only (it stops at 100 levels). Its row limit is
    lifted to the nodes there are while it runs: a tree yields each of them once."""
    parents = fs.ary_tree(s, d, 8, "part")
    parents.createOrReplaceTempView("grove_parents")
    limit = "spark.sql.cteRecursionRowLimit"
    before = s.conf.get(limit)
    if int(before) >= 0:
        s.conf.set(limit, str(max(int(before), parents.count() + 1)))
    try:
        return cut(s.sql("with recursive t(v, depth) as (select v, 0 from grove_parents where v = parent union all select p.v, t.depth + 1 from grove_parents p join t on p.parent = t.v where p.v <> p.parent) select depth, count(*) as n from t group by depth"), "depths")
    finally:
        s.conf.set(limit, before)


def string_functions(s: SparkSession, d: str) -> DataFrame:
    u = table(s, d, "pages").select("page_id", "url")
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1)
    return u.select("page_id", F.upper(host).alias("host"), F.length("url").cast("long").alias("n"), F.reverse(host).alias("back"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("pad"), F.md5("url").alias("h"), F.split(host, "\\.")[0].alias("first"))


def date_functions(s: SparkSession, d: str) -> DataFrame:
    o = table(s, d, "orders")
    return o.groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.lit("1990-01-01").cast("date"))).cast("long").alias("last_day"))


def math_functions(s: SparkSession, d: str) -> DataFrame:
    k = table(s, d, "part").select(F.col("p_partkey").alias("k"))
    return k.select("k", F.floor(F.log2(F.col("k") + 1)).cast("long").alias("lg"), F.pmod(F.col("k") * 7 - 11, F.lit(13)).alias("pm"), F.greatest(F.col("k") % 5, F.col("k") % 7).alias("g"), F.shiftright("k", 2).alias("sh"), F.bit_count("k").cast("long").alias("bits"), udfs.lowest_diff_bit(F.col("k"), F.shiftright("k", 1).bitwiseXOR(F.lit(1).cast("long"))).cast("long").alias("low"))


def array_functions(s: SparkSession, d: str) -> DataFrame:
    v = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    return v.select("vec_id", F.round(F.aggregate(F.transform("x", lambda a: a * a), F.lit(0.0), lambda a, b: a + b), 6).alias("norm2"), F.size(F.filter("x", lambda a: a > 0)).cast("long").alias("positive"), F.array_position(F.transform("x", lambda a: (a == F.array_max(F.col("x"))).cast("int")), 1).cast("long").alias("top"))


def map_and_json(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events").withColumn("m", F.from_json("props", "map<string,int>")).withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    return e.select("event_id", F.col("m")["k"].cast("long").alias("from_map"), "k", F.size(F.map_keys("m")).cast("long").alias("n_keys"))


def struct_argmin(s: SparkSession, d: str) -> DataFrame:
    o = table(s, d, "orders")
    return o.groupBy("o_custkey").agg(F.min(F.struct("o_totalprice", "o_orderkey"))["o_orderkey"].alias("cheapest"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"))


def adjacency_round_trip(s: SparkSession, d: str) -> DataFrame:
    e = fs.forest_of(fs.turn_paths(s, d)).edges
    return io.explode_adjacency(io.to_adjacency(e)).exceptAll(e).agg(F.count("*").alias("differences")).crossJoin(e.agg(F.count("*").alias("rows")))


def sql_coin(s: SparkSession, d: str) -> DataFrame:
    coins.register(s)
    table(s, d, "part").createOrReplaceTempView("grove_part")
    return s.sql("select p_partkey as id, grove_coin(p_partkey, 7, '1') as coin from grove_part")


def udtf_paths(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    fs.brand_stars(s, d).select(F.when(F.col("parent") < 0, F.col("parent")).otherwise(F.col("v")).alias("root"), "v", "parent").createOrReplaceTempView("grove_rooted")
    return s.sql("select ancestor, count(*) as n, max(dist) as far from tree_paths(table(select root, v, parent from grove_rooted) partition by root) group by ancestor")


def udtf_solve(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    t = table(s, d, "conversations").select("conv_id", (F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "turn")
    before = F.lag("id").over(W.partitionBy("conv_id").orderBy("turn"))
    t.select(F.col("conv_id").alias("leader"), F.coalesce(before, F.col("id")).alias("src"), F.col("id").alias("dst")).createOrReplaceTempView("grove_turns")
    return s.sql("select v, in_set from solve_component(table(select leader, src, dst from grove_turns) partition by leader)")


def digest_by_component(s: SparkSession, d: str) -> DataFrame:
    """Order-free digests: two orders of the same members agree in every group."""
    p = table(s, d, "part")
    a = p.groupBy("p_brand").agg(udfs.component_digest("p_partkey").alias("a"), F.count("*").alias("n"))
    b = p.orderBy(F.desc("p_partkey")).groupBy("p_brand").agg(udfs.component_digest("p_partkey").alias("b"))
    return a.join(b, "p_brand").select("p_brand", "n", (F.col("a") == F.col("b")).alias("same"))


_DEG = "with p as ({p}), e as (select v as a, parent as b from p where v <> parent union select parent, v from p where v <> parent), deg as (select n.v, count(e.a) as degree from (select v from p union select parent from p) n left join e on e.a = n.v group by n.v)"


def catalog(parents_sql: dict[str, str]) -> dict:
    """name -> (function, SQL)."""
    deg = lambda f: _DEG.format(p=parents_sql[f])
    us = "epoch_us(ts)"
    return {
        "rel_filter_predicates": (leaves_and_hubs, deg("F2") + " select v, degree, degree in (0, 1) as leaf from deg where degree in (0, 1) or degree between 5 and 99 or degree >= 100"),
        "rel_inner_join": (edge_attributes, "select c_mktsegment, count(*) as n_orders, count(distinct c_custkey) as n_customers from orders join customer on o_custkey = c_custkey group by 1"),
        "rel_full_outer_join": (outer_differences, "select c.k is not null as is_customer, o.k is not null as has_orders, count(*) as n from (select c_custkey as k from customer) c full join (select distinct o_custkey as k from orders) o on c.k = o.k group by 1, 2"),
        "rel_left_right_join": (left_right_joins, "select n_nationkey, count(s_suppkey) as n_left, count(s_suppkey) as n_right from nation left join supplier on n_nationkey = s_nationkey group by 1"),
        "rel_semi_anti_join": (semi_anti, "select (select count(*) from orders where o_orderkey in (select l_orderkey from lineitem)) as with_lines, (select count(*) from orders where o_orderkey not in (select l_orderkey from lineitem)) as without_lines"),
        "rel_theta_join": (degree_dominance, deg("F5") + ", h as (select * from deg order by degree desc, v limit 20) select x.v as a, count(*) as dominates from h x join h y on x.degree > y.degree group by 1"),
        "rel_range_join": (range_join, f"select a.user_id, count(*) as pairs from events a join events b on a.user_id = b.user_id and epoch_us(b.ts) > epoch_us(a.ts) and epoch_us(b.ts) <= epoch_us(a.ts) + 7200000000 group by 1"),
        "rel_as_of_join": (as_of_join, "select event_id, user_id, click from (select *, last_value(case when event_type = 'click' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as click from events where event_type in ('click', 'purchase')) where event_type = 'purchase'"),
        "rel_hash_aggregate": (degree_histogram_f5, deg("F5") + " select degree, count(*) as n from deg group by 1"),
        "rel_percentile_distinct": (percentiles, deg("F3") + " select cast(quantile_cont(degree, 0.5) as double) as median, count(distinct degree) as kinds, max(degree) as top from deg"),
        "rel_rollup": (revenue_rollup, "select r_name, n_name, count(*) as orders, cast(round(sum(cast(o_totalprice as decimal(18,2))), 2) as double) as revenue from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)"),
        "rel_cube": (revenue_cube, "select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube (o_orderstatus, o_orderpriority)"),
        "rel_grouping_sets": (grouping_sets, "select event_type, user_id % 5 as part, count(*) as n from events group by grouping sets ((event_type), (user_id % 5), ())"),
        "rel_pivot": (status_pivot, "select user_id % 3 as part, " + ", ".join(f"count(*) filter (event_type = '{t}') as {t}" for t in ("click", "error", "purchase", "signup", "view")) + " from events group by 1"),
        "rel_windows": (windows, "select event_id, row_number() over w as rn, ntile(4) over w as quarter, lead(event_id) over w as next_id, first_value(event_id) over w as first_id, cast(sum(1) over (partition by user_id order by ts, event_id rows between 2 preceding and current row) as bigint) as last3, rank() over (partition by event_type order by user_id) as rnk, dense_rank() over (partition by event_type order by user_id) as drnk from events window w as (partition by user_id order by ts, event_id)"),
        "rel_range_window": (range_window, "select event_id, count(*) over (partition by user_id order by sec range between 3600 preceding and current row) as in_hour from (select *, cast(floor(epoch_us(ts) / 1000000) as bigint) as sec from events)"),
        "rel_top_k": (top_hubs, deg("F6") + " select v, degree from deg order by degree desc, v limit 10"),
        "rel_top_k_per_group": (top_per_component, "select p_brand, p_partkey, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as r from part qualify r <= 3"),
        "rel_set_operations": (set_operations, "with a as (select o_custkey % 50 as k from orders), b as (select cast(c_nationkey * 3 as bigint) as k from customer) select 'union' as op, count(*) as n, cast(sum(k) as bigint) as total from (select * from a union select * from b) union all select 'union_all', count(*), cast(sum(k) as bigint) from (select * from a union all select * from b) union all select 'intersect', count(*), cast(sum(k) as bigint) from (select * from a intersect select * from b) union all select 'except', count(*), cast(sum(k) as bigint) from (select * from a except all select * from b) union all select 'minus', count(*), cast(sum(k) as bigint) from (select * from b except select * from a)"),
        "rel_subqueries": (subqueries, "select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'F') and (select count(*) from orders o where o.o_custkey = c.c_custkey) > (select count(*) from orders) / (select count(*) from customer)"),
        "rel_recursive_cte": (recursive_cte, "with recursive t(v, depth) as (select 0::bigint, 0 union all select p_partkey, t.depth + 1 from part join t on p_partkey <> 0 and (p_partkey - 1) // 8 = t.v) select depth, count(*) as n from t group by 1"),
        "fn_string": (string_functions, "select page_id, upper(host) as host, length(url) as n, reverse(host) as back, lpad(cast(page_id as varchar), 8, '0') as pad, md5(url) as h, string_split(host, '.')[1] as first from (select *, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) as host from pages)"),
        "fn_date": (date_functions, "select strftime(date_trunc('month', o_orderdate), '%Y-%m') as month, count(*) as n, max(datediff('day', date '1990-01-01', cast(o_orderdate as date))) as last_day from orders group by 1"),
        "fn_math": (math_functions, "select p_partkey as k, cast(floor(log2(p_partkey + 1)) as bigint) as lg, ((p_partkey * 7 - 11) % 13 + 13) % 13 as pm, greatest(p_partkey % 5, p_partkey % 7) as g, p_partkey >> 2 as sh, cast(bit_count(p_partkey) as bigint) as bits, cast(case when xor(p_partkey, xor(p_partkey >> 1, 1)) = 0 then 64 else bit_count((xor(p_partkey, xor(p_partkey >> 1, 1)) & -xor(p_partkey, xor(p_partkey >> 1, 1))) - 1) end as bigint) as low from part"),
        "fn_array": (array_functions, "select vec_id, round(list_sum(list_transform(cast(embedding as double[]), lambda a: a * a)), 6) as norm2, len(list_filter(embedding, lambda a: a > 0)) as positive, cast(list_position(embedding, list_max(embedding)) as bigint) as top from embeddings"),
        "fn_map_json": (map_and_json, "select event_id, cast(json_extract(props, '$.k') as bigint) as from_map, cast(json_extract(props, '$.k') as bigint) as k, cast(len(json_keys(props)) as bigint) as n_keys from events"),
        "fn_struct_argmin": (struct_argmin, "select o_custkey, arg_min(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) as cheapest, arg_max(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) as dearest from orders group by 1"),
        "src_adjacency_round_trip": (adjacency_round_trip, "select 0::bigint as differences, cast(2 * (count(*) - count(distinct conv_id)) as bigint) as rows from conversations"),
        "fn_sql_coin": (sql_coin, "select p_partkey as id, " + coins.coin_sql("p_partkey", 7, 1) + " as coin from part"),
        "udtf_tree_paths": (udtf_paths, "select -cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint) as ancestor, count(*) as n, 1 as far from part group by 1"),
        "udtf_solve_component": (udtf_solve, "select conv_id * 1000 + turn as v, (row_number() over (partition by conv_id order by turn)) % 2 = 1 as in_set from conversations"),
        "udaf_component_digest": (digest_by_component, "select p_brand, count(*) as n, true as same from part group by 1"),
    }
