"""Queries of the graph methods, measures, baselines and workloads."""

from __future__ import annotations

import math
from functools import partial

from pyspark.sql import functions as F

from .. import graphs, model
from ..functions import udfs
from ..operators import approx, baselines, blocks, cliques, exact, experiments, hashing, measures, orient, patterns, peel, primitives
from ..plans import planner
from ..storage import materialize
from . import sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name, query, oracle=None):
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def on(graph, f):
    """A query that builds the graph, writes it once and applies f."""
    return lambda spark, d: f(materialize(graphs.GRAPHS[graph](spark, d)))


def stored(graph, f):
    """The same, with the graph packed."""
    return lambda spark, d: f(blocks.stored(graphs.pairs(spark, d, graph)))


def ordered(graph, k):
    """Cliques by ordered extension; the graph is written once, packed."""
    return lambda spark, d: cliques.count_ordered(graphs.pairs(spark, d, graph), k)


BOUND5, PLAIN, SCALED = peel.schedule("from_bound", 5), peel.schedule("plain"), peel.schedule("scaled", alpha=10)

for g in graphs.GRAPHS:
    add(f"graph_stats_{g}", partial(lambda spark, d, g: experiments.graph_stats(spark, d, g), g=g), sql.stats(g))
for g in ("trade", "corun"):
    add(f"edges_{g}", graphs.GRAPHS[g], sql.on(g, select="SELECT src, dst FROM e"))
add("degree_histogram_lexical", on("lexical", lambda e: model.degrees(e).groupBy("deg").agg(F.count("*").alias("vertices"))), sql.on("lexical", sql.ARCS, sql.DEGREES, select="SELECT deg, count(*) AS vertices FROM g GROUP BY deg"))

for g in ("tripartite", "copurchase", "lexical", "sharedline", "copart30", "trade"):
    add(f"tri_rank_{g}", (lambda g: lambda spark, d: exact.count_by_rank(graphs.GRAPHS[g](spark, d)))(g), sql.triangles(g))
for g in ("lexical", "copart30", "trade"):
    add(f"tri_duplicates_{g}", on(g, lambda e: exact.count_by_duplicates(e, BOUND5).select("triangles")), sql.triangles(g))
    add(f"tri_edge_class_{g}", on(g, lambda e: exact.count_by_edge_class(e, BOUND5)), sql.triangles(g))
    trace = sql.peel_trace(g, BOUND5, 7, found=True)
    add(f"tri_uncorrected_{g}", on(g, lambda e: exact.count_by_duplicates(e, BOUND5, corrected=False)), f"SELECT CAST(sum(found2 + found4 + found6) AS BIGINT) AS raw FROM ({trace})")
    add(f"tri_class_totals_{g}", on(g, lambda e: exact.duplicates_trace(e, BOUND5)), trace)
add("tri_planned_tripartite", on("tripartite", planner.triangles), sql.triangles("tripartite"))
add("tri_by_levels_sharedline", on("sharedline", lambda e: exact.count_by_rank(e, planner.levels(e, BOUND5, small=500))), sql.triangles("sharedline"))
add("tri_list_trade", on("trade", exact.enumerate_triangles), sql.on("trade", sql.TRIANGLES, select="SELECT a, b, c FROM t"))
add("tri_list_rounds_corun", on("corun", lambda e: exact.enumerate_by_rounds(e, BOUND5)), sql.on("corun", sql.TRIANGLES, select="SELECT a, b, c FROM t"))
_low = "(SELECT v FROM g WHERE deg <= 60)"
add("tri_at_low_copurchase", on("copurchase", lambda e: planner.triangles_at(e, model.degrees(e).where("deg <= 60"))), sql.on("copurchase", sql.ARCS, sql.DEGREES, sql.TRIANGLES, select=f"SELECT a, b, c FROM t WHERE a IN {_low} OR b IN {_low} OR c IN {_low}"))
_TV = "tv AS (SELECT v, count(*) AS triangles FROM (SELECT a AS v FROM t UNION ALL SELECT b FROM t UNION ALL SELECT c FROM t) GROUP BY v)"
_CL = "y AS (SELECT g.v, deg, coalesce(triangles, 0) AS triangles, CASE WHEN deg > 1 THEN round(2 * coalesce(triangles, 0) / (deg * (deg - 1)), 6) ELSE 0.0 END AS clustering FROM g LEFT JOIN tv ON tv.v = g.v)"
add("tri_per_vertex_copart30", on("copart30", exact.per_vertex), sql.on("copart30", sql.ARCS, sql.DEGREES, sql.TRIANGLES, _TV, _CL, select="SELECT v, deg, triangles, clustering FROM y"))
add("tri_per_edge_corun", on("corun", exact.per_edge), sql.on("corun", sql.TRIANGLES, select="SELECT src, dst, coalesce(n, 0) AS support FROM e LEFT JOIN (SELECT x, y, count(*) AS n FROM (SELECT a AS x, b AS y FROM t UNION ALL SELECT a, c FROM t UNION ALL SELECT b, c FROM t) GROUP BY ALL) ON x = src AND y = dst"))
add("clustering_copart30", on("copart30", exact.clustering), sql.on("copart30", sql.ARCS, sql.DEGREES, sql.TRIANGLES, _TV, _CL, select='SELECT CAST(sum(deg * (deg - 1) // 2) AS BIGINT) AS wedges, CAST(sum(triangles) // 3 AS BIGINT) AS triangles, round(avg(clustering), 6) AS mean_local, round(sum(triangles) / sum(deg * (deg - 1) // 2), 6) AS "global" FROM y'))

for name, gamma, n in (("plain", PLAIN, 8), ("scaled", SCALED, 6), ("bound5", BOUND5, 7), ("constant", peel.schedule("constant", 60), 30)):
    q = on("tripartite", partial(lambda e, gamma: peel.levels(e, gamma).where("deg_at_removal > 0").groupBy("level").agg(F.count("*").alias("vertices"), F.sum("deg_at_removal").alias("degree_sum")), gamma=gamma))
    add(f"peel_levels_{name}_tripartite", q, sql.peel_levels("tripartite", gamma, n))
add("peel_trace_lexical", on("lexical", lambda e: measures.trace_of(e, BOUND5)), sql.peel_trace("lexical", BOUND5, 7))
add("peel_stalled_copart30", lambda spark, d: experiments.stalls(spark, d, ("copart30",)), sql.stalled("copart30"))

for g, ks in (("trade", (3, 4, 5)), ("copart30", (3, 4))):
    for k in ks:
        add(f"cliques{k}_lifted_{g}", on(g, partial(lambda e, k: cliques.count_lifted(e, k), k=k)), sql.cliques(g, k))
        add(f"cliques{k}_ordered_{g}", ordered(g, k), sql.cliques(g, k))
for k in (3, 4):
    add(f"cliques{k}_local_copart30", on("copart30", partial(lambda e, k: cliques.count_local(e, k), k=k)), sql.cliques("copart30", k))
for g, k, how in (("cosupply", 3, "ordered"), ("cosupply", 4, "ordered"), ("copurchase", 3, "ordered"), ("copurchase", 4, "ordered"), ("copurchase", 4, "lifted"), ("trade", 4, "local"), ("trade", 5, "local")):
    add(f"cliques{k}_{how}_{g}", ordered(g, k) if how == "ordered" else on(g, partial(lambda e, k, how: getattr(cliques, f"count_{how}")(e, k), k=k, how=how)), sql.cliques(g, k))
add("cliques4_ordered_sharedline", on("sharedline", planner.cliques4), sql.cliques("sharedline", 4))

_LINES = "FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM documents)"
_lines = lambda spark, d: graphs.table(spark, d, "documents").select(F.explode(F.split("text", "\n")).alias("line"))
_repeats = f"SELECT line, count(*) AS repeats {_LINES} GROUP BY line"
add("count_repeats_lines", lambda spark, d: primitives.count_repeats(_lines(spark, d), ["line"]), _repeats)
add("count_repeats_tree_lines", lambda spark, d: primitives.count_repeats_tree(_lines(spark, d), "line"), _repeats)


def _flags(spark, d):
    x = graphs.table(spark, d, "lineitem").select("l_returnflag", F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b"))
    return x.where("l_returnflag = 'R'").select("a", "b"), x.where("l_returnflag = 'A'").select("a", "b")


_MEMBER = """SELECT is_member, count(*) AS n, CAST(sum(a) AS BIGINT) AS a FROM (SELECT q.l_partkey AS a, EXISTS (SELECT 1 FROM lineitem c
WHERE c.l_returnflag = 'A' AND c.l_partkey = q.l_partkey AND c.l_suppkey = q.l_suppkey) AS is_member FROM lineitem q WHERE q.l_returnflag = 'R') GROUP BY is_member"""
for how in ("join", "sort"):
    add(f"member_{how}", partial(lambda spark, d, how: primitives.member(*_flags(spark, d), ["a", "b"], how).groupBy("is_member").agg(F.count("*").alias("n"), F.sum("a").alias("a")), how=how), _MEMBER)
add("member_semi_planned", lambda spark, d: planner.members(*_flags(spark, d), ["a", "b"]).agg(F.count("*").alias("n")), f"SELECT n FROM ({_MEMBER}) WHERE is_member")
add(
    "predecessor_events",
    lambda spark, d: primitives.predecessor(
        graphs.table(spark, d, "events").where("event_type in ('purchase', 'view')").withColumn("tag", F.when(F.col("event_type") == "purchase", 0).otherwise(1)), ["ts", "event_id"], "tag", F.col("event_id"), ["user_id"]
    ).groupBy("user_id").agg(F.count("before").alias("after_purchase"), F.sum("before").alias("before_sum")),
    """SELECT user_id, count(b) AS after_purchase, CAST(sum(b) AS BIGINT) AS before_sum FROM (SELECT user_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS)
OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS b FROM events WHERE event_type IN ('purchase', 'view')) GROUP BY user_id""",
)


def _blocks(spark, d):
    day = F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01")).alias("block")
    return graphs.table(spark, d, "orders").groupBy(day).agg(F.collect_list("o_orderkey").alias("payload"))


def _replicate_blocks(spark, d):
    keys = F.aggregate("payload", F.lit(0).cast("long"), lambda a, x: a + x)
    copies = primitives.replicate(_blocks(spark, d).withColumn("keys", keys), 10, 3)
    return copies.groupBy("copy").agg(F.count("*").alias("n"), F.sum(F.size("payload")).cast("long").alias("orders"), F.sum("keys").cast("long").alias("s"))


add("replicate_blocks", _replicate_blocks, "SELECT copy, count(DISTINCT CAST(o_orderdate AS DATE)) AS n, count(*) AS orders, CAST(sum(o_orderkey) AS BIGINT) AS s FROM orders, (SELECT unnest(range(10)) AS copy) GROUP BY copy")
add("shard_alloc_tripartite", on("tripartite", lambda e: model.degrees(e).select("v", F.greatest(F.lit(1), F.ceil(F.col("deg") * 4 / 1000)).cast("long").alias("machines")).groupBy("machines").agg(F.count("*").alias("vertices"))), sql.on("tripartite", sql.ARCS, sql.DEGREES, select="SELECT CAST(greatest(1, ceil(deg * 4 / 1000)) AS BIGINT) AS machines, count(*) AS vertices FROM g GROUP BY ALL"))
add("induced_quality", lambda spark, d: model.size(graphs.quality(spark, d)), sql.on("quality", sql.ARCS, sql.DEGREES, select="SELECT (SELECT count(*) FROM g) AS n, (SELECT count(*) FROM e) AS m"))

for g in graphs.GRAPHS:
    add(f"degeneracy_value_{g}", on(g, orient.degeneracy), sql.degeneracy(g))
    for how in ("degree", "peel", "degeneracy"):
        if g in ("corun", "copart30"):
            add(f"outdegree_max_{how}_{g}", on(g, partial(lambda e, how: orient.low_outdegree(e, how).groupBy("src").agg(F.count("*").alias("n")).agg(F.max("n").alias("most")), how=how)), sql.outdegree(g, how))
_OUT = "(SELECT max(n) FROM (SELECT count(*) AS n FROM {} GROUP BY u))"
_BY_DEGREE = "od AS (SELECT CASE WHEN (x.deg, x.v) < (y.deg, y.v) THEN src ELSE dst END AS u FROM e JOIN g x ON x.v = src JOIN g y ON y.v = dst)"
add(
    "msr_sparsity_copart30",
    on("copart30", orient.sparsity),
    sql.on("copart30", sql.ARCS, sql.DEGREES, *sql.WAVES, sql.RANKED, _BY_DEGREE, select=f"SELECT n, m, core AS degeneracy, {_OUT.format('od')} AS outdegree_by_degree, {_OUT.format('o')} AS outdegree_by_core, CAST(ceil(m / (n - 1)) AS BIGINT) AS arboricity_low, core AS arboricity_high FROM core, (SELECT count(*) AS n, CAST(sum(deg) // 2 AS BIGINT) AS m FROM g)"),
)

_NINE = ("edge", "wedge", "triangle", "path4", "claw", "cycle4", "paw", "diamond", "k4")
for name in _NINE:
    add(f"pat_{name}_corun", on("corun", partial(lambda e, name: patterns.count(e, name), name=name)), sql.pattern("corun", patterns.NAMED[name]))
for name in ("wedge", "triangle", "cycle4", "paw"):
    add(f"pat_{name}_copart30", on("copart30", partial(lambda e, name: patterns.count(e, name), name=name)), sql.pattern("copart30", patterns.NAMED[name]))
for name, p in patterns.NAMED.items():
    if p.n == 5:
        add(f"pat_{name}_corun", on("corun", partial(lambda e, name: patterns.count(e, name), name=name)), sql.pattern("corun", p))
        # nations trade with all others, a complete graph of 25 vertices: 25! / (25 - n)! labelled copies
        labelled = math.perm(25, p.n) // p.automorphisms()
        add(f"pat_{name}_trade", on("trade", partial(lambda e, name: patterns.count(e, name), name=name)), f"SELECT CAST({labelled} AS BIGINT) AS copies")
for s in range(1, 5):
    choose = {1: "CAST(sum(deg) // 2 AS BIGINT)", 2: "CAST(sum(deg * (deg - 1) // 2) AS BIGINT)", 3: "CAST(sum(CAST(deg AS HUGEINT) * (deg - 1) * (deg - 2) // 6) AS BIGINT)", 4: "CAST(sum(CAST(deg AS HUGEINT) * (deg - 1) * (deg - 2) * (deg - 3) // 24) AS BIGINT)"}[s]
    add(f"star{s}_lexical", on("lexical", partial(lambda e, s: patterns.star(e, s), s=s)), sql.on("lexical", sql.ARCS, sql.DEGREES, select=f"SELECT {choose} AS copies FROM g"))
_OR = "o AS MATERIALIZED (SELECT CASE WHEN (x.deg, x.v) < (y.deg, y.v) THEN src ELSE dst END AS u, CASE WHEN (x.deg, x.v) < (y.deg, y.v) THEN dst ELSE src END AS v FROM e JOIN g x ON x.v = src JOIN g y ON y.v = dst)"
_g = lambda e: materialize(orient.low_outdegree(e))
add("hm1_corun", on("corun", lambda e: patterns.hm1(orient.low_outdegree(e))), sql.on("corun", sql.ARCS, sql.DEGREES, _OR, select="SELECT u, v FROM o"))
add("hm2_corun", on("corun", lambda e: patterns.hm2(_g(e), 2).select(F.col("key")[0].alias("x"), F.col("key")[1].alias("y"), "cnt")), sql.on("corun", sql.ARCS, sql.DEGREES, _OR, select="SELECT p.v AS x, q.v AS y, count(*) AS cnt FROM o p JOIN o q ON p.u = q.u AND p.v < q.v GROUP BY ALL"))
add("hm3_corun", on("corun", lambda e: patterns.hm3(_g(e), 1, 1).select(F.col("key1")[0].alias("x"), F.col("key2")[0].alias("y"), "cnt")), sql.on("corun", sql.ARCS, sql.DEGREES, _OR, select="SELECT p.v AS x, q.v AS y, count(*) AS cnt FROM o JOIN o p ON p.u = o.u JOIN o q ON q.u = o.v GROUP BY ALL"))
add("tree_copies_corun", on("corun", lambda e: patterns.tree_copies(_g(e), (0, 1, 2), {1: 0, 2: 1}).select("a0", "a1", "a2")), sql.on("corun", sql.ARCS, sql.DEGREES, _OR, select="SELECT p.u AS a0, p.v AS a1, q.v AS a2 FROM o p JOIN o q ON q.u = p.v"))
add("msr_copies_corun", on("corun", lambda e: measures.copies(patterns.tree_copies(_g(e), (0, 1, 2), {1: 0, 2: 0}), e.count(), orient.degeneracy(e).first()[0] * 2, 3)), sql.on("corun", sql.ARCS, sql.DEGREES, _OR, select="SELECT count(*) AS listed, true AS within FROM o p JOIN o q ON q.u = p.u AND q.v <> p.v"))
add("pat_induced4_corun", on("corun", patterns.induced4), sql.union(f"SELECT '{n}' AS pattern, x.copies, y.copies AS induced FROM ({sql.pattern('corun', patterns.NAMED[n])}) x, ({sql.induced('corun', patterns.NAMED[n])}) y" for n in patterns.FOUR))
add("pat_extend_corun", lambda spark, d: blocks.extended(graphs.pairs(spark, d, "corun")), sql.on("corun", sql.ARCS, sql.DEGREES, _OR, select="SELECT p.u AS a0, p.v AS a1, q.v AS a2 FROM o p JOIN o q ON q.u = p.v JOIN o s ON s.u = p.u AND s.v = q.v"))
add("pat_disconnected_corun", on("corun", patterns.disconnected), sql.on("corun", sql.ARCS, sql.TRIANGLES, select="SELECT (SELECT count(*) FROM e x JOIN e y ON (x.src, x.dst) < (y.src, y.dst) AND x.src NOT IN (y.src, y.dst) AND x.dst NOT IN (y.src, y.dst)) AS two_edges, (SELECT count(*) FROM t JOIN e ON src NOT IN (a, b, c) AND dst NOT IN (a, b, c)) AS edge_and_triangle"))
# fixed values: pattern, vertices, edges, automorphisms, orientation classes, classes by out-tree size
CATALOGUE = """edge 2 1 2 1 2:1|wedge 3 2 2 3 3:2 2:1|triangle 3 3 6 1 3:1|claw 4 3 6 4 4:2 3:1 2:1|path4 4 3 2 4 4:2 3:2|paw 4 4 2 6 4:4 3:2|cycle4 4 4 8 3 4:2 3:1
diamond 4 5 4 6 4:5 3:1|k4 4 6 24 1 4:1|star4 5 4 24 5 5:2 4:1 3:1 2:1|fork 5 4 2 12 5:4 4:5 3:3|path5 5 4 2 10 5:3 4:3 3:4|cricket 5 5 4 9 5:4 4:3 3:2|bull 5 5 2 12 5:5 4:6 3:1
triangle_tail2 5 5 2 12 5:5 4:5 3:2|banner 5 5 2 18 5:9 4:8 3:1|cycle5 5 5 10 3 5:2 4:1|dart 5 6 2 24 5:13 4:9 3:2|butterfly 5 6 8 6 5:3 4:2 3:1|kite 5 6 2 18 5:10 4:8
house 5 6 2 21 5:15 4:6|k23 5 6 12 10 5:6 4:3 3:1|book3 5 7 12 10 5:7 4:2 3:1|k4_pendant 5 7 6 8 5:5 4:3|gem 5 7 2 27 5:20 4:7|wheel4_minus_spoke 5 7 4 18 5:14 4:4
k5_minus_path 5 8 4 18 5:15 4:3|wheel4 5 8 8 15 5:12 4:3|k5_minus_edge 5 9 12 10 5:9 4:1|k5 5 10 120 1 5:1"""
_rows = [r.split(" ", 5) for r in CATALOGUE.replace("\n", "|").split("|")]
add("pat_catalogue", lambda spark, d: patterns.catalogue(graphs.table(spark, d, "region").select("r_regionkey")), "SELECT * FROM (VALUES " + ", ".join(f"('{n}', {', '.join(v)}, '{t}')" for n, *v, t in _rows) + ") AS t(pattern, vertices, edges, automorphisms, classes, trees) WHERE vertices <= (SELECT count(DISTINCT r_regionkey) FROM region)")

EXPLICIT = dict(mode="explicit", p=0.1, machines=20, k=6)
_P = approx.Plan(1, 1, 0, 0.1, 20, 6, 0.5, "explicit")  # for the SQL, which takes n, m and the space from the graph
_fair = lambda g, reps: (*sql.fair_space(0.1), *sql.sampled(g, _P, reps, sql.FAIR))
_EST = "SELECT rep, CAST(sampled AS BIGINT) AS sampled, kept, overflowed, hits, round(estimate, 6) AS estimate FROM r"
_MID = "SELECT round(list_sort(list(estimate))[(len(list(estimate)) - 1) // 2 + 1], 6) AS estimate FROM "
_plan = lambda e: approx.for_graph(e, **EXPLICIT)
_rounded = lambda df: df.withColumn("estimate", F.round("estimate", 6))
_int = lambda df: df.select("rep", *[F.col(c).cast("long").alias(c) for c in ("sampled", "kept", "overflowed", "hits")], "estimate")
add("approx_once_copurchase", stored("copurchase", lambda e: _int(_rounded(approx.estimate_once(e, _plan(e))))), sql.on("copurchase", *_fair("copurchase", 1), select=_EST))
add("approx_overflow_copurchase", stored("copurchase", lambda e: _int(_rounded(approx.estimates(e, _plan(e), 4)))), sql.on("copurchase", *_fair("copurchase", 4), select=_EST))
add("approx_median_copurchase", stored("copurchase", lambda e: approx.estimate_median(e, _plan(e), 4).select(F.round("estimate", 6).alias("estimate"))), sql.on("copurchase", *_fair("copurchase", 4), select=_MID + "r WHERE estimate IS NOT NULL"))
add("approx_mom_copurchase", stored("copurchase", lambda e: approx.estimate_mom(e, _plan(e), 3, 2).select(F.round("estimate", 6).alias("estimate"))), sql.on("copurchase", *_fair("copurchase", 6), select=_MID + "(SELECT avg(estimate) AS estimate FROM r GROUP BY rep % 3) WHERE estimate IS NOT NULL"))
_SENT = "SELECT CAST(rep AS INTEGER) AS rep, i, src, dst FROM s"
_T = approx.Plan(25, 300, 1000, 0.3, 12, 6, 0.5, "explicit", 2, "explicit")
for how in ("lists", "inline", "pairs"):
    add(f"approx_{how}_trade", on("trade", partial(lambda e, how: approx.assign(e, _T, how=how), how=how)), sql.on("trade", *sql.sampled("trade", _T), select=_SENT))
add("approx_planned_trade", on("trade", lambda e: planner.samples(e, _T)), sql.on("trade", *sql.sampled("trade", _T), select=_SENT))
add("approx_arrow_trade", on("trade", lambda e: udfs.local_triangles(approx.assign(e, _T)).where("hits > 0")), sql.on("trade", *sql.sampled("trade", _T), select="SELECT rep, i, hits FROM h"))
for name in ("wedge", "cycle4", "k4"):
    add(f"approx_pattern_{name}_trade", on("trade", partial(lambda e, name: _int(_rounded(approx.estimates_of(e, name, _T, 2))), name=name)), sql.sampled_pattern("trade", patterns.NAMED[name], _T, 2))
# the repetitions that the guarantee asks for, 100 ln n
_REPS = approx.repetitions(25)
add("approx_median_full_trade", on("trade", lambda e: approx.estimate_median(e, _T, _REPS).select(F.round("estimate", 6).alias("estimate"))), sql.on("trade", *sql.sampled("trade", _T, _REPS), select=_MID + "r WHERE estimate IS NOT NULL"))
for policy in ("lemma", "budget"):
    # machines by either policy for a pattern of four vertices, at a probability that keeps the lemma's number small
    _R = partial(approx.plan, 25, 300, space=300, mode="explicit", p=0.75, k=6, eps=1.0, vertices=4, replicas=policy)()
    add(f"approx_replicas_{policy}_trade", on("trade", partial(lambda e, p: _int(_rounded(approx.estimates_of(e, "cycle4", p, 2))), p=_R)), sql.sampled_pattern("trade", patterns.NAMED["cycle4"], _R, 2))

_LN = "ln(greatest(2, n))"
_PLANS = {
    # k, space, p, machines
    "theory": (f"greatest(2, ceil(6 * {_LN}))", "floor(15.0 * sqrt(m * k) / 0.5)", "0.05 * sqrt(space / (m * k))", "ceil(20 / (0.25 * pow(p, 2)))"),
    "experiment": (f"greatest(2, floor(6.5 * {_LN}))", f"floor(2 * pow(m, 0.5) * {_LN})", "0.2 * sqrt(space / (m * k))", "ceil(floor(2 * m * ln(m)) / space)"),
    "linear": (f"greatest(2, ceil(6 * {_LN}))", f"floor(100 * n * {_LN})", "0.05 * sqrt(space / (m * k))", "ceil(20 / (0.25 * pow(p, 2)))"),
}


def _plan_sql(graph, mode):
    k, space, p, machines = _PLANS[mode]
    verdict = f"""concat_ws('; ', CASE WHEN space >= m THEN 'the graph fits one machine' END, CASE WHEN space < 15 * sqrt(m * k) / 0.5 THEN 'space under the bound for heavy vertices' END,
CASE WHEN space < 100 * k * n * n / m THEN 'space under the bound for light edges' END, CASE WHEN machines < ceil(20 / (0.25 * pow(p, 2))) THEN 'fewer machines than the lemma asks for' END)"""
    steps = f"""SELECT *, CAST(greatest(1, {machines}) AS BIGINT) AS machines FROM (SELECT *, least(1.0, {p}) AS p FROM (SELECT *, CAST({space} AS BIGINT) AS space FROM (SELECT *, CAST({k} AS INTEGER) AS k
FROM (SELECT count(*) AS n, CAST(sum(deg) // 2 AS BIGINT) AS m, max(v) + 1 AS ids FROM g))))"""
    return sql.on(graph, sql.ARCS, sql.DEGREES, select=f"SELECT n, m, space, p, machines, k, CAST(0.5 AS DOUBLE) AS eps, '{mode}' AS mode, 1 AS seed, coalesce(nullif({verdict}, ''), 'guaranteed') AS verdict, ids FROM ({steps})")


for mode in ("theory", "experiment", "linear"):
    add(f"approx_plan_{mode}_tripartite", on("tripartite", partial(lambda e, mode: approx.plan_row(e.sparkSession, approx.for_graph(e, mode=mode)), mode=mode)), _plan_sql("tripartite", mode))

_HEAVY = "y AS (SELECT s.rep, s.i, count(*) AS edges, count(*) FILTER (WHERE x.deg < 6 / 0.1 AND z.deg < 6 / 0.1) AS light FROM s JOIN g x ON x.v = s.src JOIN g z ON z.v = s.dst GROUP BY ALL)"
_LOAD = "SELECT count(*) AS nonempty, max(edges) AS most_edges, count(*) FILTER (WHERE edges > space) AS overflowed, count(*) FILTER (WHERE light * 4 > 3 * space) AS light_over, count(*) FILTER (WHERE (edges - light) * 8 > space) AS heavy_over FROM y, sp"
_COPIES = "cp AS (SELECT e.src, e.dst, count(s.i) AS copies FROM e LEFT JOIN s ON s.src = e.src AND s.dst = e.dst GROUP BY ALL)"
_OVER = "SELECT round(avg(copies), 6) AS mean, max(copies) AS most, round(avg(copies) / (any_value(space) * 20.0 / any_value(m)), 6) AS over_fair_share FROM cp, sp"
add("approx_load_copurchase", on("copurchase", lambda e: measures.load(approx.load_profile(e, _plan(e)))), sql.on("copurchase", *_fair("copurchase", 1), _HEAVY, select=_LOAD))
add("approx_sent_copurchase", on("copurchase", lambda e: approx.copies_per_edge(e, _plan(e))), sql.on("copurchase", *sql.sampled("copurchase", _P), select="SELECT copies, count(*) AS edges FROM (SELECT e.src, e.dst, count(s.i) AS copies FROM e LEFT JOIN s ON s.src = e.src AND s.dst = e.dst GROUP BY ALL) GROUP BY copies"))


def _sent(e):
    p = _plan(e)
    return measures.sent(approx.copies_per_edge(e, p), p)


add("msr_sent_copurchase", on("copurchase", _sent), sql.on("copurchase", *_fair("copurchase", 1), _COPIES, select=_OVER))
for g in ("tripartite", "cosupply"):
    add(f"approx_overflow_{g}", stored(g, lambda e: _int(_rounded(approx.estimates(e, _plan(e), 4)))), sql.on(g, *_fair(g, 4), select=_EST))
    add(f"approx_load_{g}", on(g, lambda e: measures.load(approx.load_profile(e, _plan(e)))), sql.on(g, *_fair(g, 1), _HEAVY, select=_LOAD))
    add(f"msr_sent_{g}", on(g, _sent), sql.on(g, *_fair(g, 1), _COPIES, select=_OVER))

for name, f in (("brute", baselines.brute), ("two_round", baselines.two_round), ("one_round", baselines.one_round), ("sweep", baselines.vertex_sweep), ("intersection", baselines.edge_intersection)):
    add(f"base_{name}_copart30", on("copart30", f), sql.triangles("copart30"))
add("base_folklore_copart30", on("copart30", lambda e: baselines.folklore(e, 10)), sql.triangles("copart30"))
add("base_constant_copart30", on("copart30", lambda e: baselines.peel_constant(e, 20).select("triangles")), sql.triangles("copart30"))
add("base_pattern_brute_corun", on("corun", lambda e: patterns.brute(e, "cycle4")), sql.pattern("corun", patterns.NAMED["cycle4"]))
_C = hashing.coefficients(4, 1, 0)
_col = lambda v: f"{hashing.kwise_sql(f'({v} % {hashing.P31})', _C)} % 3"
add("base_colour_copurchase", on("copurchase", lambda e: baselines.colour_partition(e, 3)), sql.on("copurchase", f"c AS MATERIALIZED (SELECT src, dst, {_col('src')} AS i FROM e WHERE {_col('src')} = {_col('dst')})", select="SELECT CAST(0 AS INTEGER) AS rep, count(*) AS hits, count(*) * 9.0::DOUBLE AS estimate FROM c x JOIN c y ON y.src = x.dst JOIN c z ON z.src = x.src AND z.dst = y.dst"))
add("base_wedge_copurchase", on("copurchase", lambda e: baselines.wedge_sampling(e, 2000)))

for g in experiments.ROUND_GRAPHS:
    add(f"exp_rounds_{g}", partial(lambda spark, d, g: experiments.rounds(spark, d, g), g=g), sql.rounds(g, experiments.ROUND_GRAPHS[g]))
add("exp_factor_050", lambda spark, d: experiments.factors(spark, d, experiments.FACTOR_GRAPHS, 0.5))
add("exp_factor_075", lambda spark, d: experiments.factors(spark, d, (*experiments.FACTOR_GRAPHS, "lexical"), 0.75))
add("exp_hash_ablation", experiments.hash_ablation)
add("exp_hash_ablation_sharedline", lambda spark, d: experiments.hash_ablation(spark, d, "sharedline"))
_B = approx.Plan(1, 1, 1 << 40, 0.05, 20, 6, 0.5, "explicit")
_ERR = "abs(estimate - t) / t"
add("exp_below_alb_vecsim", lambda spark, d: experiments.below_bound(spark, d), sql.on("vecsim", *sql.sampled("vecsim", _B, 20), sql.TRIANGLES, "tt AS (SELECT count(*) AS t FROM t)", select=f"SELECT count(*) AS runs, round(avg({_ERR}), 6) AS mean_error, round(avg(CASE WHEN {_ERR} <= 0.5 THEN 1.0 ELSE 0.0 END), 6) AS coverage, round(pow(0.05, 3.0) * any_value(t) * 20, 6) AS expected_hits FROM r, tt"))
add("exp_patterns_corun", lambda spark, d: experiments.pattern_suite(spark, d, "corun", _NINE), " UNION ALL ".join(f"SELECT '{n}' AS pattern, copies FROM ({sql.pattern('corun', patterns.NAMED[n])})" for n in _NINE))
for g in ("trade", "copart30", "custpart"):
    add(f"exp_patterns_{g}", partial(lambda spark, d, g: experiments.pattern_suite(spark, d, g, _NINE), g=g), sql.union(f"SELECT '{n}' AS pattern, copies FROM ({sql.pattern(g, patterns.NAMED[n])})" for n in _NINE))
add("exp_stalls", lambda spark, d: experiments.stalls(spark, d, tuple(graphs.GRAPHS)), sql.union(sql.stalled(g) for g in graphs.GRAPHS))
add("exp_correction", lambda spark, d: experiments.correction(spark, d, tuple(graphs.GRAPHS)), sql.union(sql.correction(g) for g in graphs.GRAPHS))
add("exp_graph_table", experiments.graph_table, sql.union(f"SELECT x.*, y.degeneracy FROM ({sql.stats(g)}) x, ({sql.degeneracy(g)}) y" for g in graphs.GRAPHS))
add("exp_scaling_tripartite", lambda spark, d: experiments.scaling(spark, d).drop("exchanges"), sql.union(sql.on("tripartite", f"h AS MATERIALIZED (SELECT src, dst FROM e WHERE src % 4 < {k} AND dst % 4 < {k})", select=f"SELECT {k} AS part, (SELECT count(*) FROM h) AS edges, (SELECT count(*) FROM h x JOIN h y ON x.dst = y.src JOIN h z ON z.src = x.src AND z.dst = y.dst) AS triangles") for k in range(1, 5)))
add("exp_cost_copart30", on("copart30", lambda e: measures.cost_table(e.sparkSession, {"rank": exact.count_by_rank(e), "brute": baselines.brute(e), "one round": baselines.one_round(e), "intersection": baselines.edge_intersection(e)})))
add("exp_choice_tripartite", on("tripartite", planner.explain_choice), sql.on("tripartite", sql.ARCS, sql.DEGREES, select="SELECT n, m, max_degree, square_sum, CASE WHEN max_degree <= 64 * greatest(1.0, 2 * m / n) THEN 'degree order' ELSE 'peeling levels, then degree' END AS method FROM (SELECT count(*) AS n, CAST(sum(deg) // 2 AS BIGINT) AS m, max(deg) AS max_degree, CAST(sum(deg * deg) AS BIGINT) AS square_sum FROM g)"))

_TR = sql.peel_trace("copart30", BOUND5, 7)
add("msr_iterations_copart30", on("copart30", lambda e: measures.iterations(measures.trace_of(e, BOUND5))), f"SELECT count(*) AS iterations FROM ({_TR})")
add("msr_message_bound_copart30", on("copart30", lambda e: measures.message_bound(measures.trace_of(e, BOUND5))), f"SELECT round, messages, messages <= 2 * edges * gamma + 1e-6 AS within FROM ({_TR})")
add("msr_total_space_copart30", on("copart30", lambda e: measures.total_space(measures.trace_of(e, BOUND5))), f"SELECT CAST(sum(messages) + 2 * max(edges) AS BIGINT) AS words, round(2 * max(edges) * ln(max(edges)), 6) AS cap FROM ({_TR})")
_DECAY = sql.on("copart30", *sql.trace("copart30", "20 * pow(2.0, pow(1.5, it))"), select="""SELECT CAST(it AS INTEGER) AS round, vertices, edges, vertices <= (max(vertices) OVER ()) / pow(2.0, 2 * (pow(1.5, it) - 1)) + 1e-6 AS vertices_ok,
edges <= (max(edges) OVER ()) / (CASE WHEN it > 0 THEN pow(2.0, 2 * (pow(1.5, it - 1) - 1)) ELSE 1 END) + 1e-6 AS edges_ok FROM tr""")
add("msr_decay_copart30", on("copart30", lambda e: measures.decay(measures.trace_of(e, SCALED))), _DECAY)
add("msr_space_copart30", on("copart30", lambda e: measures.spaces(e.sparkSession, *model.size(e).first())), sql.on("copart30", sql.ARCS, sql.DEGREES, select="SELECT mode, delta, CAST(floor(CASE mode WHEN 'nodes' THEN pow(n, delta) ELSE 2 * pow(m, delta) * ln(n) END) AS BIGINT) AS space FROM (VALUES ('nodes', 0.3::DOUBLE), ('nodes', 0.5), ('nodes', 0.9), ('edges', 0.5), ('edges', 0.75)) AS t(mode, delta), (SELECT count(*) AS n, sum(deg) // 2 AS m FROM g)"))
add("msr_model_rounds_copart30", on("copart30", lambda e: measures.model_rounds(measures.trace_of(e, BOUND5), {f"n^{s}": e.select("src").union(e.select("dst")).distinct().count() ** s for s in (0.3, 0.5, 0.9)})), sql.on("copart30", *sql.trace("copart30", "pow(5.0, pow(1.5, it))"), "sp AS (SELECT d, pow(CAST((SELECT count(DISTINCT src) FROM a) AS DOUBLE), d) AS s FROM (SELECT unnest([0.3, 0.5, 0.9])::DOUBLE AS d))", select=f"SELECT 'n^' || d AS space, CAST(sum({sql.MODEL_ROUNDS}) AS BIGINT) AS rounds FROM (SELECT *, messages + 2 * edges AS big FROM tr, sp) GROUP BY d"))
add("msr_theory_copurchase", on("copurchase", lambda e: measures.theory_row(e.sparkSession, _plan(e), blocks.count(e).first()[0])), sql.on("copurchase", sql.TRIANGLES, select="SELECT round(pow(0.1, 3) * n * 20, 6) AS expected_hits, round(pow(0.1, 3) * n + pow(0.1, 4) * n * n, 6) AS sample_variance, round(least(1.0, 2 / (0.25 * pow(0.1, 2) * 20)), 6) AS chebyshev FROM (SELECT count(*)::DOUBLE AS n FROM t)"))
add("msr_alb_copart30", on("copart30", lambda e: measures.alb(e, 1000)), sql.on("copart30", sql.ARCS, sql.DEGREES, select="SELECT round(sqrt(sum(deg) / 2 / 1000), 6) AS root_m_over_s, round(sum(deg) / count(*), 6) AS mean_degree, CAST(sum(deg * deg) AS BIGINT) AS square_sum FROM g"))


def _registered(spark, text):
    udfs.register(spark)
    return spark.sql(text)


add("udtf_orientations", lambda spark, d: _registered(spark, "SELECT k, arcs, automorphisms, tree FROM orientations('cycle4')"))
add("udtf_schedule", lambda spark, d: _registered(spark, "SELECT round, gamma FROM peel_schedule('constant', 4.0D, 3)"), "SELECT CAST(unnest(range(3)) AS INTEGER) AS round, 4.0::DOUBLE AS gamma")


def _udtf_pairs(spark, d):
    udfs.register(spark)
    graphs.table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.collect_list("l_partkey").alias("ps")).createOrReplaceTempView("subcount_orders")
    return spark.sql("SELECT l_orderkey, p.a, p.b FROM subcount_orders, LATERAL pairs(ps) p")


add("udtf_pairs", _udtf_pairs, "WITH x AS (SELECT DISTINCT l_orderkey, l_partkey AS v FROM lineitem) SELECT x.l_orderkey, x.v AS a, y.v AS b FROM x JOIN x y ON x.l_orderkey = y.l_orderkey AND x.v < y.v")
_K61 = hashing.coefficients(3, 7, 0, hashing.P61)
add("udf_kwise_arrow", lambda spark, d: graphs.table(spark, d, "nation").select("n_nationkey", udfs.kwise61(_K61)(F.col("n_nationkey").cast("long")).alias("h"), hashing.kwise(F.col("n_nationkey").cast("long"), _K61, hashing.P61).alias("h_decimal")), f"SELECT n_nationkey, h, h AS h_decimal FROM (SELECT n_nationkey, CAST((((CAST({_K61[0]} AS HUGEINT) * n_nationkey + {_K61[1]}) % {hashing.P61}) * n_nationkey + {_K61[2]}) % {hashing.P61} AS BIGINT) AS h FROM nation)")
