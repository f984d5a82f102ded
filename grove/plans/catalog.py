"""The engine's own queries and their SQL, by name.

Certificates are rows of counts that must equal what SQL says whatever the coins were."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from grove import cost
from grove.functions import udfs
from grove.functions.coins import SIDES, coin_sql, threshold
from grove.operators import baselines as bl
from grove.operators import degree as dg
from grove.operators import extras as ex
from grove.operators.clique import clique_gather, neighbourhood
from grove.operators.gather import colocate, component_of, gather, inspace_gather, pack_components
from grove.operators.graph import Forest, assign_ids, component_labels, degrees, induced, is_forest, max_degree, require_forest, two_hop
from grove.operators.labels import contract_labels, flood_labels, minset_labels
from grove.operators.ledger import RoundLedger
from grove.operators.pointers import jump_to_root
from grove.operators.rooting import budget_round, root_forest, tree_edges
from grove.operators.shatter import desire_round, shatter
from grove.operators.verify import certify_colouring, certify_matching, certify_mis
from grove.params import TreeMisParams
from grove.plans import relational
from grove.plans import workloads as wl
from grove.plans.tree_mis import finish, tree_mis, with_hub_cleanup
from grove.session import cut, table
from grove.sources import forests as fs
from grove.streaming import queries as st

T = fs.TAG
_U = "((k * 1103515245 + 12345) % 2147483648)"
_K = "(select o_orderkey as k from orders)"
_LINES = "(select distinct l_orderkey, l_orderkey * 10 + l_linenumber as line from lineitem)"
#: parents(v, parent) of each forest, for DuckDB.
PARENTS = {
    "F1": f"select 0::bigint as v, 0::bigint as parent union all select {T} + r_regionkey, 0 from region union all select {2 * T} + n_nationkey, {T} + n_regionkey from nation "
    f"union all select {3 * T} + c_custkey, {2 * T} + c_nationkey from customer union all select {4 * T} + o_orderkey, {3 * T} + o_custkey from orders union all select {5 * T} + line, {4 * T} + l_orderkey from {_LINES}",
    "F2": "select p_partkey as v, -cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint) as parent from part union all select distinct -cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint), -cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint) from part",
    "F3": "select event_id as v, coalesce(lag(event_id) over (partition by user_id order by ts, event_id), event_id) as parent from events",
    "F4": f"select o_orderkey as v, coalesce(lag(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey), o_orderkey) as parent from orders union all select {5 * T} + line, l_orderkey from {_LINES}",
    "F5": f"select k as v, case when k = 0 then 0 else {_U} % k end as parent from {_K}",
    "F6": f"select k as v, ((((k * {_U}) >> 31) * {_U}) >> 31) * {_U} >> 31 as parent from {_K}",
    "F7": f"select k as v, case when k = 0 then 0 else (k - 1) // 8 end as parent from {_K}",
    "F8": "select conv_id * 1000 + turn as v, coalesce(lag(conv_id * 1000 + turn) over (partition by conv_id order by turn), conv_id * 1000 + turn) as parent from conversations",
    "F9": "select cast('0x' || substr(md5(key), 1, 15) as bigint) as v, cast('0x' || substr(md5(pk), 1, 15) as bigint) as parent from (select '' as key, '' as pk union select array_to_string(s[1:i], '/'), array_to_string(s[1:i-1], '/') from "
    "(select s, unnest(range(1, len(s) + 1)) as i from (select list_concat(list_reverse(string_split(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.')), list_filter(string_split(regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1), '/'), lambda x: x <> '')) as s from pages)))",
    "F10": "select event_id as v, coalesce(lag(event_id) over (order by ts, event_id), event_id) as parent from events",
    "F11": "select v, coalesce(parent, v) as parent from (select a.vec_id as v, arg_max(b.vec_id, struct_pack(c := list_cosine_similarity(cast(a.embedding as double[]), cast(b.embedding as double[])), n := -b.vec_id)) as parent from embeddings a left join embeddings b on b.vec_id < a.vec_id group by 1)",
}
EDGES = {
    "G1": "select doc_id as a, min(doc_id) over (partition by text) as b from documents",
    "G2": f"select distinct {3 * T} + o_custkey as a, {6 * T} + l_suppkey as b from lineitem join orders on l_orderkey = o_orderkey",
}


def _both(f: str) -> str:
    """CTEs p, n(v) and e(src, dst) of a forest or graph."""
    if f in PARENTS:
        return f"p as ({PARENTS[f]}), n as (select v from p union select parent from p), e as (select v as src, parent as dst from p where v <> parent union select parent, v from p where v <> parent)"
    return f"q as ({EDGES[f]}), n as (select a as v from q union select b from q), e as (select a as src, b as dst from q where a <> b union select b, a from q where a <> b)"


def _rooted(f: str) -> str:
    """p and r(v, root, depth) by recursion; for shallow trees."""
    return f"p as ({PARENTS[f]}), r(v, root, depth) as (select v, v, 0::bigint from p where v = parent union all select p.v, r.root, r.depth + 1 from p join r on p.parent = r.v where p.v <> p.parent)"


def forest(s: SparkSession, d: str, f: str) -> Forest:
    return fs.forest_of(fs.FORESTS[f](s, d)).cut()


def graph(s: SparkSession, d: str, f: str) -> Forest:
    return Forest.of(fs.GRAPHS[f](s, d)).cut()


def flagship(s: SparkSession, d: str) -> DataFrame:
    """(v, root, depth) of the random recursive tree."""
    return jump_to_root(fs.recursive_tree(s, d))


def rooting_certificate(g: Forest, parents: DataFrame) -> DataFrame:
    """(n_nodes, pointed, edges_used, roots, trees): every node points, along tree edges, to one root a tree."""
    at = cut(parents, "parents")
    used = at.where("v <> parent").join(g.edges, (F.col("v") == F.col("src")) & (F.col("parent") == F.col("dst"))).count()
    roots = jump_to_root(at).select("root").distinct().count()
    trees = component_labels(g).select("leader").distinct().count()
    row = (g.nodes.count(), at.select("v").distinct().count(), used, roots, trees)
    return g.nodes.sparkSession.createDataFrame([row], "n_nodes long, pointed long, edges_used long, roots long, trees long")


def _one(s: SparkSession, **values: int) -> DataFrame:
    return s.createDataFrame([tuple(int(x) for x in values.values())], ", ".join(f"{k} long" for k in values))


def _cert_sql(f: str) -> str:
    return f"with {_both(f)} select (select count(*) from n) as n_nodes, (select count(*) // 2 from e) as n_edges, 0::bigint as inside_edges, 0::bigint as undominated"


def _mis(run: Callable, f: str) -> Callable:
    def q(s: SparkSession, d: str) -> DataFrame:
        g = graph(s, d, f) if f in fs.GRAPHS else forest(s, d, f)
        return certify_mis(g, cut(run(s, d, g), "set"))

    return q


def conquer_cert(s: SparkSession, d: str) -> DataFrame:
    g = forest(s, d, "F6")
    p = TreeMisParams(gather="clique")
    deg = max_degree(g)
    chosen, rest, _ = dg.conquer_step(g, p, 0, deg)
    sampled = dg.sample_nodes(g.nodes, deg, p.sampling_exponent(), p.seed, 0)
    inside = induced(g, chosen).edges.count()
    return _one(s, n_nodes=g.nodes.count(), inside_edges=inside, sampled_left=sampled.join(rest.nodes, "v", "left_semi").count())


def degree_trace_cert(s: SparkSession, d: str) -> DataFrame:
    g, p = forest(s, d, "F6"), TreeMisParams(gather="clique")
    _, rest, trace = dg.reduce_degree(g, p)
    rises = sum(after > before for _, before, after, *_ in trace)
    return _one(s, n_nodes=g.nodes.count(), rises=rises, over_floor=max_degree(rest) > p.floor_for(g.nodes.count()))


def shatter_cert(s: SparkSession, d: str) -> DataFrame:
    g = forest(s, d, "F5")
    chosen, rest = shatter(g, 8)
    chosen = cut(chosen, "set")
    touched = rest.nodes.join(g.edges.join(chosen.withColumnRenamed("v", "src"), "src", "left_semi").select(F.col("dst").alias("v")).unionByName(chosen), "v", "left_semi").count()
    return _one(s, n_nodes=g.nodes.count(), inside_edges=induced(g, chosen).edges.count(), left_next_to_set=touched)


def finish_sizes(s: SparkSession, d: str) -> DataFrame:
    """A maximum set of every star of F2, solved in tasks."""
    g = forest(s, d, "F2")
    got = finish(g, "label", "dp")
    labels = component_labels(g)
    return got.join(labels, "v").groupBy("leader").agg(F.count("*").alias("size"))


def hub_split_f6(s: SparkSession, d: str) -> DataFrame:
    dd = degrees(forest(s, d, "F6"))
    return dd.groupBy((F.col("degree") >= 12).alias("hub")).agg(F.count("*").alias("n"), F.sum("degree").alias("total"))


def hub_cert(s: SparkSession, d: str) -> DataFrame:
    g = forest(s, d, "F2")
    n, p = g.nodes.count(), TreeMisParams(gather="clique")
    out, left = with_hub_cleanup(g, p)
    c = certify_mis(g, out).first()
    return _one(s, n_nodes=n, inside_edges=c.inside_edges, undominated=c.undominated, over_bound=left[0] > 2 * (n - 1) / p.hub_degree(n))


def clique_rounds(s: SparkSession, d: str) -> DataFrame:
    ledger = RoundLedger()
    clique_gather(forest(s, d, "F8"), ledger)
    return _one(s, rounds=ledger.rounds())


def clique_growth(s: SparkSession, d: str) -> DataFrame:
    g, ledger = forest(s, d, "F8"), RoundLedger()
    labels = clique_gather(g, ledger)
    k3 = labels.groupBy("leader").count().agg(F.sum(F.pow("count", F.lit(3)))).first()[0]
    pairs = labels.groupBy("leader").count().agg(F.sum(F.col("count") * (F.col("count") - 1) / 2)).first()[0]
    made = sum(r[9] for r in ledger.rows)
    return _one(s, over_k3=ledger.copies() > k3, over_pairs=made > pairs, pairs=pairs, tree_and_made=made + g.edges.count() // 2)


def budget_round_f4(s: SparkSession, d: str) -> DataFrame:
    g = forest(s, d, "F4")
    new, _ = budget_round(tree_edges(g.edges), g.nodes.withColumn("left", F.lit(6).cast("long")))
    return new.select("src", "dst", "hop_out", "hop_in")


def rooting(f: str, budget: int) -> Callable:
    def q(s: SparkSession, d: str) -> DataFrame:
        g = forest(s, d, f)
        return rooting_certificate(g, root_forest(g, budget))

    return q


def phase_invariant(s: SparkSession, d: str) -> DataFrame:
    g, ledger = forest(s, d, "F4"), RoundLedger()
    root_forest(g, 8, ledger=ledger, strict_budget=True)
    n0 = g.nodes.count()
    return _one(s, n_nodes=n0, over_mass=sum(r[6] * r[7] > n0 * 8 for r in ledger.rows), copies_over_mass=sum(r[8] > n0 * 8 for r in ledger.rows))


def pack_cert(s: SparkSession, d: str) -> DataFrame:
    sizes = component_labels(forest(s, d, "F3")).groupBy("leader").agg(F.count("*").alias("size"))
    loads = pack_components(sizes, 200).groupBy("bin").agg(F.sum("size").alias("load"), F.count("*").alias("k"))
    return loads.agg(F.sum("k").alias("components"), F.sum("load").alias("nodes"), F.sum((F.col("load") > 200).cast("long")).alias("over"))


def shatter_round_f5(s: SparkSession, d: str) -> DataFrame:
    g = forest(s, d, "F5")
    return desire_round(g, g.nodes.withColumn("e", F.lit(1)), 7, 0)


def bit_round_f5(s: SparkSession, d: str) -> DataFrame:
    p = fs.recursive_tree(s, d)
    return bl.bit_reduction_round(p.withColumn("c", F.col("v"))).select("v", "c")


def small_subtrees(s: SparkSession, d: str) -> DataFrame:
    """For sizes a: nodes with a subtree of at most a, and whether they are at least n a / (depth + a)."""
    sizes = cut(ex.subtree_sizes(fs.recursive_tree(s, d)), "sizes")
    n, top = sizes.count(), jump_to_root(fs.recursive_tree(s, d)).agg(F.max("depth")).first()[0]
    a = s.createDataFrame([(x,) for x in (1, 2, 4, 8, 16, 32)], "a long")
    return sizes.join(a, F.col("size") <= F.col("a")).groupBy("a").agg(F.count("*").alias("small")).select("a", "small", (F.col("small") * (F.col("a") + top) >= F.col("a") * n).alias("enough"))


def sampled_sizes(s: SparkSession, d: str) -> DataFrame:
    g = forest(s, d, "F6")
    return dg.sampled_components(g, dg.sample_nodes(g.nodes, 4, 1.0, 7))


def labels_of(run: Callable, f: str) -> Callable:
    return lambda s, d: run(graph(s, d, f) if f in fs.GRAPHS else forest(s, d, f))


def sample_report(s: SparkSession, d: str) -> DataFrame:
    """(leader, size, diameter) of the components that the sample induces."""
    g = forest(s, d, "F6")
    sub = induced(g, dg.sample_nodes(g.nodes, 4, 1.0, 7)).cut()
    rooted = cut(root_forest(sub, 64, 16), "rooted")
    far = ex.diameters(rooted, sub)
    labels = cut(component_labels(sub), "labels")
    return labels.groupBy("leader").agg(F.count("*").alias("size")).join(far.join(labels.withColumnRenamed("v", "root"), "root").select("leader", "diameter"), "leader")


def hub_sample(s: SparkSession, d: str) -> DataFrame:
    """(v, degree, sampled) of the nodes of degree 12 and more."""
    g = forest(s, d, "F6")
    return dg.sampled_degrees(g, dg.sample_nodes(g.nodes, 4, 1.0, 7), 12)


def colocated(s: SparkSession, d: str) -> DataFrame:
    """Whole components lie in one file of the written table, bins within their capacity."""
    g = forest(s, d, "F3")
    at = colocate(g.nodes, component_labels(g), capacity=200).withColumn("f", F.input_file_name())
    one = at.groupBy("bin").agg(F.count("*").alias("load"), F.countDistinct("f").alias("files"))
    return one.agg(F.sum("load").alias("nodes"), F.sum((F.col("load") > 200).cast("long")).alias("over"), F.sum((F.col("files") > 1).cast("long")).alias("torn"))


def assigned(s: SparkSession, d: str) -> DataFrame:
    """Ids for the urls of the pages, with their audit."""
    ids = assign_ids(table(s, d, "pages").select("url").distinct(), "url")
    return ids.agg(F.count("*").alias("keys"), F.countDistinct("id").alias("ids"))


def given_sizes(s: SparkSession, d: str) -> list[int]:
    """Nodes of F5, of F10 and of the lines of F1: the sizes that the model's arithmetic is about."""
    keys = (("orders", F.col("o_orderkey")), ("events", F.col("event_id")), ("lineitem", F.col("l_orderkey") * 10 + F.col("l_linenumber")))
    return [table(s, d, t).agg(F.countDistinct(k)).first()[0] for t, k in keys]


def queries_with_sql() -> dict[str, tuple[Callable, str | None]]:
    q: dict[str, tuple[Callable, str | None]] = {"root_and_depth": (flagship, f"with recursive {_rooted('F5')} select v, root, depth from r")}
    for f in PARENTS:
        q[f"forest_edges_{f}"] = (lambda s, d, f=f: fs.forest_of(fs.FORESTS[f](s, d)).edges, f"with {_both(f)} select src, dst from e")
    for f in EDGES:
        q[f"graph_edges_{f}"] = (lambda s, d, f=f: Forest.of(fs.GRAPHS[f](s, d)).edges, f"with {_both(f)} select src, dst from e")
    q["graph_edges_G3"] = (lambda s, d: Forest.of(fs.GRAPHS["G3"](s, d)).edges, None)
    for f in ("F1", "F2", "F6", "G2"):
        q[f"degree_histogram_{f}"] = (
            lambda s, d, f=f: degrees(graph(s, d, f) if f in fs.GRAPHS else forest(s, d, f)).groupBy("degree").agg(F.count("*").alias("n")),
            f"with {_both(f)} select degree, count(*) as n from (select n.v, count(e.src) as degree from n left join e on e.src = n.v group by n.v) group by degree",
        )
    q["max_degree"] = (
        lambda s, d: s.createDataFrame([(f, max_degree(forest(s, d, f))) for f in ("F1", "F5", "F6")], "forest string, delta long"),
        " union all ".join(f"select '{f}' as forest, (with {_both(f)} select max(c) from (select count(*) as c from e group by src)) as delta" for f in ("F1", "F5", "F6")),
    )
    q["forest_check"] = (
        lambda s, d: s.createDataFrame([(f, is_forest(graph(s, d, f) if f in fs.GRAPHS else forest(s, d, f))) for f in ("F1", "F9", "G2")], "name string, acyclic boolean"),
        "select * from (values ('F1', true), ('F9', true), ('G2', false)) t(name, acyclic)",
    )
    p4 = threshold(1 / 4)
    sam = f"s as (select v from n where {coin_sql('v', 7, 'sample0')} < {p4})"
    q["sampled_nodes"] = (lambda s, d: dg.sample_nodes(forest(s, d, "F6").nodes, 4, 1.0, 7), f"with {_both('F6')}, {sam} select v from s")
    q["sampled_induced_edges"] = (
        lambda s, d: (lambda g: induced(g, dg.sample_nodes(g.nodes, 4, 1.0, 7)).edges)(forest(s, d, "F6")),
        f"with {_both('F6')}, {sam} select src, dst from e where src in (select v from s) and dst in (select v from s)",
    )
    q["sampled_component_report"] = (
        sampled_sizes,
        f"with recursive {_both('F6')}, {sam}, t(v, root) as (select s.v, s.v from s join p using (v) where p.v = p.parent or p.parent not in (select v from s) union all "
        "select p.v, t.root from p join t on p.parent = t.v join s on s.v = p.v where p.v <> p.parent) select min(v) as leader, count(*) as size from t group by root",
    )
    within = f"with recursive {_both('F6')}, {sam}, w as (select s.v, case when p.v <> p.parent and p.parent in (select v from s) then p.parent end as up from s join p using (v)), t(v, root) as (select v, v from w where up is null union all select w.v, t.root from w join t on w.up = t.v)"
    q["sample_report"] = (
        sample_report,
        within + ", h(v, a, c, k) as (select v, v, v, 0::bigint from w union all select h.v, w.up, w.v, h.k + 1 from h join w on w.v = h.a where w.up is not null), b as (select a, c, max(k) as k from h group by a, c), "
        "f as (select a as v, list_sum(list_sort(list(k), 'DESC')[1:2]) as far from b group by a), z as (select root, min(v) as leader, count(*) as size from t group by root) "
        "select leader, any_value(size) as size, cast(max(far) as bigint) as diameter from t join f using (v) join z using (root) group by leader",
    )
    q["sampled_degrees_of_hubs"] = (hub_sample, f"with {_both('F6')}, {sam} select src as v, count(*) as degree, count(*) filter (dst in (select v from s)) as sampled from e group by src having count(*) >= 12")
    q["colocate_cert"] = (colocated, "select count(*) as nodes, 0::bigint as over, 0::bigint as torn from events")
    q["assigned_ids_cert"] = (assigned, "select count(distinct url) as keys, count(distinct url) as ids from pages")
    q["udf_lowest_diff_bit"] = (
        lambda s, d: table(s, d, "orders").select("o_orderkey", udfs.lowest_diff_bit_pandas("o_orderkey", F.shiftright("o_orderkey", 1)).alias("bit")),
        "select o_orderkey, cast(bit_count((x & -x) - 1) as int) as bit from (select o_orderkey, xor(o_orderkey, o_orderkey >> 1) as x from orders)",
    )
    q["udaf_mis_weight"] = (
        lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").agg(udfs.mis_weight("o_orderkey", F.col("o_orderkey") % 2 == 0).alias("weight")),
        "select o_orderpriority, cast(sum(case when o_orderkey % 2 = 0 then o_orderkey else 0 end) as bigint) as weight from orders group by 1",
    )
    q["neighbour_independence"] = (
        lambda s, d: (lambda g: dg.neighbour_independence(g, dg.sample_nodes(g.nodes, 4, 1.0, 7)))(forest(s, d, "F6")),
        f"with {_both('F6')}, {sam} select src as v, count(*) as sampled_neighbours, count(*) as components from e where dst in (select v from s) and src not in (select v from s) group by src",
    )
    q["coin_colouring_rooted"] = (
        lambda s, d: dg.coin_colouring_rooted(flagship(s, d), 7),
        f"with recursive {_rooted('F5')} select v, root as leader, (depth + ({coin_sql('root', 7, 'colour')} & 1)) % 2 = 0 as black from r",
    )
    q["coin_colouring_local"] = (
        lambda s, d: (lambda g: dg.coin_colouring(g, component_labels(g), 7))(forest(s, d, "F8")),
        f"with t as (select conv_id * 1000 + turn as v, min(conv_id * 1000 + turn) over (partition by conv_id) as leader, row_number() over (partition by conv_id order by turn) - 1 as depth from conversations) select v, leader, (depth + ({coin_sql('leader', 7, 'colour')} & 1)) % 2 = 0 as black from t",
    )
    zero = lambda f, *names: f"with {_both(f)} select (select count(*) from n) as n_nodes, " + ", ".join(f"0::bigint as {x}" for x in names)
    q["conquer_step_cert"] = (conquer_cert, zero("F6", "inside_edges", "sampled_left"))
    q["degree_trace_cert"] = (degree_trace_cert, zero("F6", "rises", "over_floor"))
    marked = f"m as (select v, {coin_sql('v', 7, 'mark0')} < {SIDES // 2} as marked from n)"
    q["shatter_round"] = (
        shatter_round_f5,
        f"with {_both('F5')}, {marked}, a as (select e.src as v, bool_or(m.marked) as any_marked, 0.5 * count(*) as total from e join m on m.v = e.dst group by e.src) "
        "select m.v, case when coalesce(total, 0) >= 2 then 2 else 1 end as e, marked and not coalesce(any_marked, false) as joins from m left join a using (v)",
    )
    q["shatter_cert"] = (shatter_cert, zero("F5", "inside_edges", "left_next_to_set"))
    q["finish_cert"] = (_mis(lambda s, d, g: finish(g, "clique", "greedy"), "F8"), _cert_sql("F8"))
    q["finish_colour_cert"] = (_mis(lambda s, d, g: finish(g, "label", "colour"), "F8"), _cert_sql("F8"))
    q["finish_dp_size"] = (finish_sizes, "select -cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint) as leader, count(*) as size from part group by 1")
    q["tree_maximum_size"] = (lambda s, d: ex.tree_max_independent_set(fs.turn_paths(s, d)).groupBy("size").agg(F.count("*").alias("trees")), "select cast((n + 1) // 2 as bigint) as size, count(*) as trees from (select conv_id, count(*) as n from conversations group by 1) group by 1")
    q["hub_split"] = (hub_split_f6, f"with {_both('F6')} select degree >= 12 as hub, count(*) as n, cast(sum(degree) as bigint) as total from (select n.v, count(e.src) as degree from n left join e on e.src = n.v group by n.v) group by 1")
    q["hub_cleanup_cert"] = (hub_cert, zero("F2", "inside_edges", "undominated", "over_bound"))
    turn_labels = "select conv_id * 1000 + turn as v, min(conv_id * 1000 + turn) over (partition by conv_id) as leader from conversations"
    twins = "select doc_id as v, min(doc_id) over (partition by text) as leader from documents"
    for name, run in {"clique_gather": clique_gather, "inspace_gather": lambda g: inspace_gather(g, 8), "flood_labels": flood_labels, "minset_labels": minset_labels, "contract_labels": contract_labels, "star_labels": component_labels}.items():
        q[f"{name}_F8"] = (labels_of(run, "F8"), turn_labels)
        if name != "inspace_gather":
            q[f"{name}_G1"] = (labels_of(run, "G1"), twins)
    q["gather_dispatch_F2"] = (labels_of(lambda g: gather(g, "auto"), "F2"), f"with {_both('F2')} select v, case when v < 0 then v else (select parent from p where p.v = n.v) end as leader from n")
    q["component_of_F8"] = (lambda s, d: component_of(forest(s, d, "F8"), 8), turn_labels)
    q["inspace_gather_F1"] = (labels_of(lambda g: inspace_gather(g, 10, 50), "F1"), f"with {_both('F1')} select v, 0::bigint as leader from n")
    q["clique_rounds"] = (clique_rounds, "select cast(ceil(log2(max(n - 1))) + 1 as bigint) as rounds from (select count(*) as n from conversations group by conv_id)")
    q["clique_growth_cert"] = (clique_growth, "select 0::bigint as over_k3, 0::bigint as over_pairs, cast(sum(n * (n - 1) // 2) as bigint) as pairs, cast(sum(n * (n - 1) // 2) as bigint) as tree_and_made from (select count(*) as n from conversations group by conv_id)")
    q["budget_round_F4"] = (
        budget_round_f4,
        f"with {_both('F4')}, deg as (select src, count(*) as c from e group by src), m as (select src from deg where c * (c - 1) // 2 <= 6) "
        "select distinct a.dst as src, b.dst as dst, a.src as hop_out, a.src as hop_in from e a join e b on a.src = b.src and a.dst <> b.dst where a.src in (select src from m)",
    )
    for name, f, b in (("F1", "F1", 50), ("F2", "F2", 8), ("F4", "F4", 27), ("F5", "F5", 64), ("F8", "F8", 343), ("F1_small_budget", "F1", 4)):
        q[f"rooting_cert_{name}"] = (
            rooting(f, b),
            f"with {_both(f)}, t as (select (select count(*) from n) as n, (select count(*) // 2 from e) as m) select n as n_nodes, n as pointed, m as edges_used, n - m as roots, n - m as trees from t",
        )
    q["phase_invariant"] = (phase_invariant, zero("F4", "over_mass", "copies_over_mass"))
    q["pointer_root_depth_F6"] = (lambda s, d: jump_to_root(fs.hub_tree(s, d)), f"with recursive {_rooted('F6')} select v, root, depth from r")
    q["pointer_root_depth_F3"] = (lambda s, d: jump_to_root(fs.event_chains(s, d)), "select event_id as v, first_value(event_id) over w as root, row_number() over w - 1 as depth from events window w as (partition by user_id order by ts, event_id)")
    q["pointer_root_depth_F10"] = (lambda s, d: jump_to_root(fs.time_line(s, d)), "select event_id as v, first_value(event_id) over w as root, row_number() over w - 1 as depth from events window w as (order by ts, event_id)")
    q["pack_cert"] = (pack_cert, "select count(distinct user_id) as components, count(*) as nodes, 0::bigint as over from events")
    q["two_hop_pairs"] = (lambda s, d: two_hop(forest(s, d, "F8")), f"with {_both('F8')} select distinct a.dst as src, b.dst as dst from e a join e b on a.src = b.src and a.dst <> b.dst where not exists (select 1 from e c where c.src = a.dst and c.dst = b.dst)")
    q["three_hop_balls"] = (
        lambda s, d: neighbourhood(forest(s, d, "F8"), 3),
        "with t as (select conv_id, conv_id * 1000 + turn as v, row_number() over (partition by conv_id order by turn) as i from conversations) select a.v, b.v as w from t a join t b on a.conv_id = b.conv_id and a.i <> b.i and abs(a.i - b.i) <= 3",
    )
    for f in ("F1", "F2", "F4", "F5", "F6", "F7", "F8"):
        q[f"tree_mis_clique_{f}"] = (_mis(lambda s, d, g: tree_mis(g, gather="clique"), f), _cert_sql(f))
        q[f"tree_mis_inspace_{f}"] = (_mis(lambda s, d, g: tree_mis(g, gather="inspace", diameter=8), f), _cert_sql(f))
    q["small_memory_cert"] = (_mis(lambda s, d, g: tree_mis(g, gather="clique", mem_exp=0.4, hub_cleanup=True), "F6"), _cert_sql("F6"))
    base = {
        "solo_mis": lambda s, d, g: bl.solo_mis(g),
        "priority_mis": lambda s, d, g: bl.priority_mis(g),
        "fixed_order_mis": lambda s, d, g: bl.priority_mis(g, fresh=False),
        "marking_mis": lambda s, d, g: bl.marking_mis(g),
        "tree_local_mis": lambda s, d, g: bl.tree_local_mis(g),
        "rooted_mis": lambda s, d, g: bl.rooted_mis(g, fs.recursive_tree(s, d)),
        "prefix_greedy_mis": lambda s, d, g: bl.prefix_greedy_mis(g),
        "ball_gather_mis": lambda s, d, g: bl.ball_gather_mis(g),
        "local_rounds_mis": lambda s, d, g: bl.finish_by_local_rounds(g),
    }
    for name, run in base.items():
        q[f"{name}_cert"] = (_mis(run, "F8" if name == "ball_gather_mis" else "F5"), _cert_sql("F8" if name == "ball_gather_mis" else "F5"))
    q["priority_mis_cert_G2"] = (_mis(lambda s, d, g: bl.priority_mis(g), "G2"), _cert_sql("G2"))
    q["priority_round"] = (
        lambda s, d: bl.priority_round(forest(s, d, "F5"), 7, "priority0"),
        f"with {_both('F5')}, c as (select v, {coin_sql('v', 7, 'priority0')} as c from n), b as (select e.src as v, min(struct_pack(p := c.c, id := c.v)) as q from e join c on c.v = e.dst group by e.src) select c.v from c left join b using (v) where q is null or struct_pack(p := c.c, id := c.v) < q",
    )
    x = "xor(v, case when v = parent then xor(v, 1) else parent end)"
    q["bit_reduction_round"] = (bit_round_f5, f"with p as ({PARENTS['F5']}), i as (select v, cast(bit_count(({x} & -{x}) - 1) as bigint) as i from p) select v, cast(2 * i + ((v >> i) & 1) as bigint) as c from i")
    q["small_subtree_lemma"] = (
        small_subtrees,
        f"with recursive {_rooted('F5')}, up(v, a) as (select v, v from p union all select up.v, p.parent from up join p on p.v = up.a where p.v <> p.parent), z as (select a as v, count(*) as size from up group by a), "
        "s as (select * from (values (1), (2), (4), (8), (16), (32)) t(a)), k as (select (select count(*) from z) as n, (select max(depth) from r) as top) "
        "select cast(s.a as bigint) as a, count(*) as small, count(*) * (s.a + any_value(top)) >= s.a * any_value(n) as enough from s join z on z.size <= s.a cross join k group by s.a",
    )
    q["diameter_F3"] = (lambda s, d: ex.diameters(fs.event_chains(s, d), None).select("diameter"), "select count(*) - 1 as diameter from events group by user_id")
    q["diameter_F1"] = (lambda s, d: ex.diameters(fs.commerce_tree(s, d), None).select("diameter"), "select 10::bigint as diameter")
    sizes = "(select count(distinct o_orderkey) as n from orders union all select count(distinct event_id) from events union all select count(distinct l_orderkey * 10 + l_linenumber) from lineitem)"
    q["mpc_plan"] = (
        lambda s, d: cost.mpc_plans(s, given_sizes(s, d)),
        f"select variant, n, s as local_memory, m as machines, s * m as total from (select variant, n, cast(round(pow(n, 0.5)) as bigint) as s, cast(round(case when variant = 'clique' then pow(n, 1 - 0.5 / 3) else pow(n, 0.5) end) as bigint) as m from {sizes}, (select unnest(['clique', 'inspace']) as variant))",
    )
    lg, ll = "log2(n)", "log2(log2(n))"
    formulas = {
        "clique": f"pow({ll}, 2)", "inspace": f"pow({ll}, 3)", "small_memory": f"pow({ll}, 2) / 0.5", "priority": lg, "tree_local": f"sqrt({lg}) * {ll}", "rooted": "case when n <= 65536 then 4 else 5 end", "prefix": ll, "ball": f"sqrt({lg})",
        "local_finish": f"pow(2, sqrt({ll}))", "gather_clique": "6", "gather_inspace": f"5 * {ll}", "flood": "32", "reduction_steps": "ln(6) / ln(1.5)", "sparse_matching": f"pow({ll}, 2)", "arboricity": f"sqrt({lg})", "list_colouring": f"sqrt({ll})", "lower_bound": ll,
    }
    q["predicted_rounds"] = (
        lambda s, d: cost.predictions(s, given_sizes(s, d)),
        " union all ".join(f"select '{m}' as method, n, round(cast({f} as double), 6) as rounds from {sizes}" for m, f in formulas.items()),
    )
    q["matching_cert"] = (lambda s, d: (lambda g: certify_matching(g.edges, cut(ex.maximal_matching(g), "m")))(forest(s, d, "F5")), "select 0::bigint as shared_ends, 0::bigint as addable")
    q["line_graph_edges"] = (lambda s, d: ex.line_graph(forest(s, d, "F8"))[1].edges.agg(F.count("*").alias("n")), "select cast(sum(greatest(n - 2, 0)) * 2 as bigint) as n from (select count(*) as n from conversations group by conv_id)")
    q["colouring_cert"] = (lambda s, d: (lambda g: certify_colouring(g, ex.degree_colouring(g)))(forest(s, d, "F5")), "select 0::bigint as uncoloured, 0::bigint as clashes, 0::bigint as colours_over")
    q["edge_colouring_cert"] = (
        lambda s, d: (lambda g: ex.edge_colouring(g).agg(F.count("*").alias("edges"), (F.max("c") > 2).cast("long").alias("colours_over")))(forest(s, d, "F8")),
        "select cast(sum(n - 1) as bigint) as edges, 0::bigint as colours_over from (select count(*) as n from conversations group by conv_id)",
    )
    q["two_colour_cert"] = (lambda s, d: (lambda g: certify_colouring(g, ex.two_colour(g, 8)))(forest(s, d, "F8")), "select 0::bigint as uncoloured, 0::bigint as clashes, 0::bigint as colours_over")
    for name in wl.WORKLOADS:
        q[f"workload_{name}"] = (wl.query(name), wl.sql(name))
    q["workload_w14_application"] = (
        lambda s, d: wl.w14_application(s, d).select("user_id", "events", "total", ((F.col("chosen") * 3 >= F.col("events")) & (F.col("chosen") * 2 <= F.col("events") + 1)).alias("in_bounds")),
        "select user_id, count(*) as events, round(sum(value), 4) as total, true as in_bounds from events group by 1",
    )
    q |= relational.catalog(PARENTS)
    q |= st.catalog()
    return q


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, (f, _) in queries_with_sql().items()}


def oracle_sql() -> dict[str, str]:
    return {k: sql for k, (_, sql) in queries_with_sql().items() if sql is not None}


__all__ = ["flagship", "oracle_sql", "queries", "require_forest", "table"]
