"""All graph queries by name, and the SQL that states the same for DuckDB."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import agreement, complete, functions, plans, quality, streaming, tracking
from .components import components
from .generators import PlantedPartition, PlantedTable, edges_sql, labels_sql, planted_edges, planted_labels
from .linalg import block_eigs, centred
from .linalg import lanczos as distributed_lanczos
from .operators import DeformedLaplacian, Laplacian, ModularityOp, MultisliceModularityOp, NonBacktracking, spmv
from .plans.leiden import Distributed, null_strengths, slice_rates, summed
from .plans.spectral import lloyd_step
from .session import cut
from .sources import edges as files
from .sources import load, planted as planted_source, register_views
from .streaming.build import run_to_table
from .supra import SupraGraph, couple, dataset_properties, degrees, meeting_properties, sid, slice_totals, strengths, supra_graph, supra_size
from .temporal import TemporalGraph, absent_nodes, active_nodes, backbone, between_slices, contacts_within, ego, flatten, index_nodes, index_slices, induced, min_weight, presence, slice_edges, snapshot
from .workloads import EVENTS_FROM, WORKLOADS, sweep

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

#: The graph that most queries run on, and the small one for whole methods.
BASE, SMALL = "cosupp_quarter", "nation_trade_year_thinned"


def query(name: str, sql: str | None = None):
    def register(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return register


def graph(spark: SparkSession, sf_dir: str, name: str = BASE) -> TemporalGraph:
    w = WORKLOADS[name]
    return TemporalGraph(w.build(spark, sf_dir), w.directed, meta={"workload": name}, active=w.active and w.active(spark, sf_dir), complete=w.complete)


def rule_labels(nodes: DataFrame) -> DataFrame:
    """A labelling by rule that changes with time: (node + slice / 9) mod 5."""
    return nodes.select("slice", "node", F.pmod(F.col("node") + F.floor(F.col("slice") / 9), F.lit(5)).alias("community"))


def static_labels(edges: DataFrame) -> DataFrame:
    return active_nodes(edges).select("node").distinct().withColumn("community", F.pmod("node", F.lit(5)))


def based(spark: SparkSession, sf_dir: str, name: str = BASE) -> tuple[TemporalGraph, DataFrame]:
    tg = graph(spark, sf_dir, name)
    return tg, rule_labels(tg.nodes)


def with_graph(body: str, name: str = BASE) -> str:
    """SQL over e (edges), n (temporal nodes), l (labels), k (strengths), ties (couplings) and ends (edges with both labels)."""
    return f"""WITH e AS (SELECT slice, src, dst, weight FROM {WORKLOADS[name].sql}),
  n AS (SELECT DISTINCT slice, node FROM (SELECT slice, src AS node FROM e UNION ALL SELECT slice, dst FROM e)),
  l AS (SELECT slice, node, ((node + slice // 9) % 5)::BIGINT AS community FROM n),
  k AS (SELECT slice, node, sum(weight) AS k FROM (SELECT slice, src AS node, weight FROM e UNION ALL SELECT slice, dst, weight FROM e) GROUP BY ALL),
  ties AS (SELECT slice AS slice_a, slice_b, node FROM (SELECT slice, node, lead(slice) OVER (PARTITION BY node ORDER BY slice) AS slice_b FROM n) WHERE slice_b = slice + 1),
  ends AS (SELECT e.*, a.community AS ca, b.community AS cb FROM e JOIN l a ON a.slice = e.slice AND a.node = e.src JOIN l b ON b.slice = e.slice AND b.node = e.dst)
  {body}"""


def with_flat(body: str, name: str = BASE) -> str:
    """SQL over f (the flattened graph), l (node, community), ends, c (size, volume, inside and cut of each community)."""
    return f"""WITH f AS (SELECT src, dst, sum(weight) AS weight FROM {WORKLOADS[name].sql} GROUP BY ALL),
  both_ends AS (SELECT src AS node, weight FROM f UNION ALL SELECT dst, weight FROM f),
  k AS (SELECT node, sum(weight) AS k, count(*) AS links FROM both_ends GROUP BY node),
  l AS (SELECT node, (node % 5)::BIGINT AS community FROM k),
  ends AS (SELECT f.*, (src % 5)::BIGINT AS ca, (dst % 5)::BIGINT AS cb FROM f),
  c AS (SELECT community, (SELECT count(*) FROM l WHERE l.community = g.community) AS size, sum(weight) AS volume,
          sum(CASE WHEN other = community THEN weight ELSE 0 END) AS inside, sum(CASE WHEN other <> community THEN weight ELSE 0 END) AS cut
        FROM (SELECT ca AS community, cb AS other, weight FROM ends UNION ALL SELECT cb, ca, weight FROM ends) g GROUP BY community)
  {body}"""


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


def _sid(slice_: str, node: str) -> str:
    return f"({slice_}::BIGINT * 1099511627776 + {node})"


SUPRA_SQL = f"""s AS (
    SELECT {_sid("slice", "src")} AS a, {_sid("slice", "dst")} AS b, weight, 's' AS kind FROM e
    UNION ALL SELECT {_sid("slice", "dst")}, {_sid("slice", "src")}, weight, 's' FROM e
    UNION ALL SELECT {_sid("slice_a", "node")}, {_sid("slice_b", "node")}, 1.0, 't' FROM ties
    UNION ALL SELECT {_sid("slice_b", "node")}, {_sid("slice_a", "node")}, 1.0, 't' FROM ties)"""

# ---------------------------------------------------------------- construction


@query("slice_edges", "SELECT datediff('day', DATE '2024-01-01', ts::DATE)::INT AS slice, user_id AS src, (event_id % 7) + 1000000 AS dst, count(*)::DOUBLE AS weight FROM events GROUP BY ALL")
def _(spark, sf):
    rows = load(spark, sf, "events").select("ts", "user_id", (F.col("event_id") % 7 + 1_000_000).alias("thing"))
    return slice_edges(rows, "ts", "day", "user_id", "thing", origin=EVENTS_FROM).edges


@query("slice_edges_sum_directed", "SELECT year(o_orderdate)::INT - 1995 AS slice, o_custkey AS src, l_suppkey AS dst, round(sum(l_quantity), 6) AS weight FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderdate >= TIMESTAMP '1997-01-01' AND o_custkey <> l_suppkey GROUP BY ALL")
def _(spark, sf):
    rows = load(spark, sf, "orders").filter("o_orderdate >= '1997-01-01'").join(load(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return rounded(slice_edges(rows, "o_orderdate", "year", "o_custkey", "l_suppkey", "sum:l_quantity", "1995-01-01", directed=True).edges, "weight")


@query("index_slices", with_graph("SELECT (dense_rank() OVER (ORDER BY slice) - 1)::INT AS slice, src, dst, weight FROM e", "contact_10min"))
def _(spark, sf):
    tg = graph(spark, sf, "contact_10min")
    return index_slices(tg.edges, "close", tg.nodes)


@query("index_nodes", "SELECT p_brand AS name, (row_number() OVER (ORDER BY p_brand) - 1)::BIGINT AS ix FROM (SELECT DISTINCT p_brand FROM part)")
def _(spark, sf):
    return index_nodes(load(spark, sf, "part").select("p_brand"), ["p_brand"])[1]


@query("presence_span", with_graph("SELECT range::INT AS slice, node FROM (SELECT node, min(slice) AS lo, max(slice) AS hi FROM n GROUP BY node), range(100) WHERE range BETWEEN lo AND hi"))
def _(spark, sf):
    return presence(graph(spark, sf).edges, "span")


@query("node_slice_grid", with_graph("SELECT s.slice, v.node FROM (SELECT DISTINCT slice FROM n) s, (SELECT DISTINCT node FROM n) v"))
def _(spark, sf):
    return presence(graph(spark, sf).edges, "all")


@query("coupling_edges", with_graph("SELECT slice_a, slice_b, node, 0.5::DOUBLE AS weight FROM ties"))
def _(spark, sf):
    return couple(graph(spark, sf).nodes, 0.5)


@query("coupling_next_seen", with_graph("SELECT slice AS slice_a, slice_b, node, 1.0::DOUBLE AS weight FROM (SELECT slice, node, lead(slice) OVER (PARTITION BY node ORDER BY slice) AS slice_b FROM n) WHERE slice_b IS NOT NULL", "contact_hour"))
def _(spark, sf):
    return couple(graph(spark, sf, "contact_hour").nodes, 1.0, "next_seen")


@query("coupling_all", with_graph("SELECT a.slice AS slice_a, b.slice AS slice_b, a.node, 1.0::DOUBLE AS weight FROM n a JOIN n b ON a.node = b.node AND a.slice < b.slice", SMALL))
def _(spark, sf):
    return couple(graph(spark, sf, SMALL).nodes, 1.0, "all")


@query("coupling_table", with_graph("SELECT a.slice AS slice_a, b.slice AS slice_b, a.node, round(1.0 / (b.slice - a.slice), 6)::DOUBLE AS weight FROM n a JOIN n b ON a.node = b.node AND b.slice - a.slice BETWEEN 1 AND 2", SMALL))
def _(spark, sf):
    tg = graph(spark, sf, SMALL)
    s = tg.edges.select("slice").distinct()
    table = s.withColumnRenamed("slice", "slice_a").crossJoin(F.broadcast(s.withColumnRenamed("slice", "slice_b"))).filter("slice_b - slice_a between 1 and 2").withColumn("omega", F.round(1.0 / (F.col("slice_b") - F.col("slice_a")), 6))
    return couple(tg.nodes, table, "table")


@query("supra_edges", with_graph(f", {SUPRA_SQL} SELECT a, b, weight::DOUBLE AS weight, kind FROM s"))
def _(spark, sf):
    return supra_graph(graph(spark, sf)).edges


@query("degrees", with_graph(f", {SUPRA_SQL} SELECT a AS sid, sum(CASE WHEN kind = 's' THEN weight ELSE 0 END)::DOUBLE AS d_s, sum(CASE WHEN kind = 't' THEN weight ELSE 0 END)::DOUBLE AS d_t, sum(weight)::DOUBLE AS d FROM s GROUP BY a"))
def _(spark, sf):
    return degrees(supra_graph(graph(spark, sf))).select("sid", "d_s", "d_t", "d")


@query("degrees_all", with_graph("SELECT g.slice, g.node, coalesce(k.k, 0)::DOUBLE AS k FROM (SELECT s.slice, v.node FROM (SELECT DISTINCT slice FROM n) s, (SELECT DISTINCT node FROM n) v) g LEFT JOIN k ON k.slice = g.slice AND k.node = g.node"))
def _(spark, sf):
    tg = graph(spark, sf)
    return presence(tg.edges, "all").join(strengths(tg.edges), ["slice", "node"], "left").select("slice", "node", F.coalesce("k_out", F.lit(0.0)).alias("k"))


@query("slice_totals", with_graph("SELECT slice, count(*) AS m, sum(weight) AS w, 2 * sum(weight) AS two_m FROM e GROUP BY slice"))
def _(spark, sf):
    return slice_totals(graph(spark, sf).edges)


@query("flatten", with_graph("SELECT 0::INT AS slice, src, dst, sum(weight) AS weight FROM e GROUP BY src, dst"))
def _(spark, sf):
    return flatten(graph(spark, sf).edges)


@query("supra_size", with_graph("SELECT (SELECT count(*) FROM n) AS nodes, (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM ties) AS couplings, 4 * (SELECT count(*) FROM e) + 4 * (SELECT count(*) FROM ties) + 6 * (SELECT count(*) FROM n) AS nb_entries"))
def _(spark, sf):
    return supra_size(supra_graph(graph(spark, sf)))


@query(
    "components",
    with_graph(
        """, p AS (SELECT DISTINCT src, dst FROM e), both_ways AS (SELECT src AS u, dst AS v FROM p UNION SELECT dst, src FROM p),
  r(node, root) AS (SELECT DISTINCT u, u FROM both_ways UNION SELECT b.v, r.root FROM r JOIN both_ways b ON b.u = r.node AND r.root < b.v)
  SELECT node, min(root) AS component FROM r GROUP BY node""",
        "page_links",
    ).replace("WITH e AS", "WITH RECURSIVE e AS"),
)
def _(spark, sf):
    return components(graph(spark, sf, "page_links").edges)


def _properties(name: str) -> None:
    w = WORKLOADS[name]
    truth = f"(SELECT count(DISTINCT label) FROM {w.truth_sql})" if w.truth_sql else "NULL::BIGINT"
    label = lambda spark, sf: w.truth(spark, sf) if w.truth and w.truth_sql else None
    sql = with_graph(f"SELECT (SELECT count(DISTINCT node) FROM n) AS v, (SELECT count(*) FROM n) AS v_sum, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM e)) AS e, (SELECT count(*) FROM e) AS e_sum, (SELECT count(DISTINCT slice) FROM e) AS t, {truth} AS c", name)
    query(f"properties_{name}", sql)(lambda spark, sf: dataset_properties(w.build(spark, sf), label(spark, sf)) if w.active is None else meeting_properties(w.active(spark, sf)))


for _name in WORKLOADS:
    _properties(_name)
QUERIES["dataset_properties"], SQL["dataset_properties"] = QUERIES[f"properties_{BASE}"], SQL[f"properties_{BASE}"]


@query("approx_nodes", with_graph("SELECT true AS close"))
def _(spark, sf):
    e = graph(spark, sf).edges
    exact, near = dataset_properties(e), dataset_properties(e, approx=True)
    return exact.select(F.col("v").alias("x")).crossJoin(near.select(F.col("v").alias("y"))).select((F.abs(F.col("x") - F.col("y")) <= 0.05 * F.col("x")).alias("close"))


#: Customers in five classes that a few leave, tied by order lines.
_PLANTED = PlantedTable(PlantedPartition(0, 5, 4, 10.0, 0.6, 0.95, seed=9))


@query("sbm_edges", "SELECT * FROM " + _PLANTED.edges_sql)
def _(spark, sf):
    return _PLANTED.edges(spark, sf)


@query("sbm_labels", "SELECT * FROM " + _PLANTED.labels_sql)
def _(spark, sf):
    return _PLANTED.labels(spark, sf)


# ---------------------------------------------------------------- measures


@query(
    "modularity",
    with_flat("""SELECT round(sum(coalesce(w, 0) * 2 / (2 * m) - vol * vol / (4 * m * m)), 6) AS q FROM
  (SELECT community, volume AS vol, inside / 2 AS w FROM c), (SELECT sum(weight) AS m FROM f)"""),
)
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.modularity(e, static_labels(e)), "q")


@query(
    "modularity_directed",
    f"""WITH e AS (SELECT src, dst, sum(weight) AS weight FROM {WORKLOADS["user_succession_day"].sql} GROUP BY ALL),
  o AS (SELECT src % 5 AS c, sum(weight) AS k FROM e GROUP BY 1), i AS (SELECT dst % 5 AS c, sum(weight) AS k FROM e GROUP BY 1),
  w AS (SELECT src % 5 AS c, sum(weight) AS w FROM e WHERE src % 5 = dst % 5 GROUP BY 1), t AS (SELECT sum(weight) AS m FROM e)
  SELECT round(sum(coalesce(w.w, 0) / m - 0.8 * coalesce(o.k, 0) * coalesce(i.k, 0) / (m * m)), 6) AS q FROM t, o FULL JOIN i USING (c) LEFT JOIN w USING (c)""",
)
def _(spark, sf):
    e = flatten(graph(spark, sf, "user_succession_day").edges)
    return rounded(quality.modularity(e, static_labels(e), 0.8, directed=True, convention="directed"), "q")


@query(
    "multislice_modularity",
    with_graph("""SELECT round((within + kept) / (sum_m + ties), 6) AS q_ms, (sum_m + ties)::DOUBLE AS two_mu FROM
  (SELECT sum(2 * coalesce(w, 0) - kk / two_m) AS within, sum(two_m) AS sum_m FROM
    (SELECT slice, 2 * sum(weight) AS two_m, sum(CASE WHEN ca = cb THEN weight ELSE 0 END) AS w FROM ends GROUP BY slice)
    JOIN (SELECT slice, sum(kc * kc) AS kk FROM (SELECT slice, community, sum(k) AS kc FROM k JOIN l USING (slice, node) GROUP BY ALL) GROUP BY slice) USING (slice)),
  (SELECT 2.0 * count(*) AS ties, 2.0 * count(*) FILTER (a.community = b.community) AS kept FROM ties t
    JOIN l a ON a.slice = t.slice_a AND a.node = t.node JOIN l b ON b.slice = t.slice_b AND b.node = t.node)"""),
)
def _(spark, sf):
    tg, labels = based(spark, sf)
    return rounded(quality.multislice_modularity(tg, labels), "q_ms")


@query("slice_modularity", with_graph("""SELECT slice, round(2 * w / two_m - kk / (two_m * two_m), 6) AS q FROM
    (SELECT slice, 2 * sum(weight) AS two_m, sum(CASE WHEN ca = cb THEN weight ELSE 0 END) AS w FROM ends GROUP BY slice)
    JOIN (SELECT slice, sum(kc * kc) AS kk FROM (SELECT slice, community, sum(k) AS kc FROM k JOIN l USING (slice, node) GROUP BY ALL) GROUP BY slice) USING (slice)"""))
def _(spark, sf):
    tg, labels = based(spark, sf)
    return rounded(quality.slice_modularity(tg.edges, labels), "q")


_SUPRA_ENDS = f""", {SUPRA_SQL}, sl AS (SELECT {_sid("slice", "node")} AS sid, community FROM l),
  se AS (SELECT s.*, x.community AS ca, y.community AS cb FROM s JOIN sl x ON x.sid = s.a JOIN sl y ON y.sid = s.b)"""


@query("supra_modularity", with_graph(f"""{_SUPRA_ENDS} SELECT round((SELECT sum(weight) FROM se WHERE ca = cb) / t - (SELECT sum(kc * kc) FROM (SELECT ca, sum(weight) AS kc FROM se GROUP BY ca)) / (t * t), 6)::DOUBLE AS q FROM (SELECT sum(weight)::DOUBLE AS t FROM se)"""))
def _(spark, sf):
    tg, labels = based(spark, sf)
    return rounded(quality.supra_modularity(supra_graph(tg), labels), "q")


@query("trace_modularity", SQL["multislice_modularity"].replace("AS q_ms, (sum_m + ties)::DOUBLE AS two_mu", "AS q"))
def _(spark, sf):
    """The trace form, by applying the multislice operator to the community indicators."""
    tg, labels = based(spark, sf)
    supra = supra_graph(tg)
    own = labels.select(sid(F.col("slice"), F.col("node")).alias("sid"), "community")
    block = own.select("sid", *(F.when(F.col("community") == c, 1.0).otherwise(0.0).alias(f"c{c}") for c in range(5)))
    image = MultisliceModularityOp(tg, supra).apply(block).withColumnsRenamed({f"c{c}": f"m{c}" for c in range(5)})
    trace = block.join(image, "sid").agg(F.sum(sum((F.col(f"c{c}") * F.col(f"m{c}") for c in range(5)), F.lit(0.0))).alias("trace"))
    mu = supra.edges.agg(F.sum("weight").alias("two_mu"))
    return trace.crossJoin(mu).select(F.round(F.col("trace") / F.col("two_mu"), 6).alias("q"))


@query("ncut", with_flat("SELECT round(sum(cut / volume), 6)::DOUBLE AS ncut FROM c"))
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.ncut(e, static_labels(e)), "ncut")


@query("rcut", with_flat("SELECT round(sum(cut / size), 6)::DOUBLE AS rcut FROM c"))
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.rcut(e, static_labels(e)), "rcut")


@query("conductance", with_flat("SELECT community, round(cut / least(volume, (SELECT sum(volume) FROM c) - volume), 6)::DOUBLE AS conductance FROM c"))
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.conductance(e, static_labels(e)), "conductance")


@query("cpm", with_flat("SELECT round(sum(inside / 2 - 0.1 * size * (size - 1) / 2), 6)::DOUBLE AS cpm FROM c"))
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.cpm(e, static_labels(e), 0.1), "cpm")


@query("multislice_cpm", with_graph("""SELECT round((SELECT sum(weight) FROM ends WHERE ca = cb) - 0.1 * (SELECT sum(s * (s - 1) / 2) FROM (SELECT slice, community, count(*) AS s FROM l GROUP BY ALL))
  + (SELECT count(*) FROM ties t JOIN l a ON a.slice = t.slice_a AND a.node = t.node JOIN l b ON b.slice = t.slice_b AND b.node = t.node WHERE a.community = b.community), 6)::DOUBLE AS cpm"""))
def _(spark, sf):
    tg, labels = based(spark, sf)
    return rounded(quality.multislice_cpm(tg, labels, 0.1), "cpm")


@query("surprise", with_flat("""SELECT round(m * (x * ln(x / y) + (1 - x) * ln((1 - x) / (1 - y))), 4)::DOUBLE AS surprise FROM (
  SELECT sum(volume) / 2 AS m, sum(inside) / sum(volume) AS x, sum(size * (size - 1) / 2) / (sum(size) * (sum(size) - 1) / 2) AS y FROM c)"""))
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.surprise(e, static_labels(e)), "surprise", digits=4)


@query("resolution_limit", with_flat("SELECT community, (inside / 2)::DOUBLE AS links, round(sqrt(2 * (SELECT sum(weight) FROM f)), 6) AS scale, inside / 2 < sqrt(2 * (SELECT sum(weight) FROM f)) AS below FROM c"))
def _(spark, sf):
    e = flatten(graph(spark, sf).edges)
    return rounded(quality.resolution_limit(e, static_labels(e)), "scale")


def _quantities(spark: SparkSession, sf: str) -> DataFrame:
    """The different quantities and line numbers of order lines: the grid on which the scalar relations are worked out."""
    return load(spark, sf, "lineitem").select(F.col("l_quantity").alias("c"), (F.col("l_linenumber") / 8.0).alias("lam")).distinct()


_GRID = "(SELECT DISTINCT l_quantity::DOUBLE AS c, l_linenumber / 8.0::DOUBLE AS lam FROM lineitem)"


@query("detectability", f"SELECT c, lam, k, round(c * lam * lam, 9)::DOUBLE AS snr, CASE WHEN c * lam * lam > 1 THEN 'detectable' WHEN k > 4 THEN 'hard or undetectable' ELSE 'undetectable' END AS regime FROM {_GRID}, (VALUES (2), (8)) d(k)")
def _(spark, sf):
    """Mean degrees are quantities, affinities eighths of line numbers."""
    grid = _quantities(spark, sf).withColumn("k", F.explode(F.array(F.lit(2), F.lit(8))))
    d = functions.detectability(F.col("c"), F.col("lam"), F.col("k"))
    return grid.select("c", "lam", "k", F.round(d.snr, 9).alias("snr"), d.regime.alias("regime"))


@query("cheeger_bounds", "SELECT lam2, round(lam2 / 2, 9)::DOUBLE AS low, round(sqrt(2 * lam2), 9)::DOUBLE AS high FROM (SELECT DISTINCT l_quantity / 25::DOUBLE AS lam2 FROM lineitem)")
def _(spark, sf):
    """Quantities, scaled to the eigenvalues that a normalised Laplacian can have."""
    b = functions.cheeger_bounds(F.col("lam2"))
    values = load(spark, sf, "lineitem").select((F.col("l_quantity") / 25.0).alias("lam2")).distinct()
    return values.select("lam2", F.round(b.low, 9).alias("low"), F.round(b.high, 9).alias("high"))


@query("sql_functions", f"SELECT c, lam AS part, round((c - 8 * lam) / 50, 9)::DOUBLE AS lam, round(c * lam * lam, 9)::DOUBLE AS snr FROM {_GRID}")
def _(spark, sf):
    functions.register(spark)
    return _quantities(spark, sf).select("c", F.col("lam").alias("part"), F.expr("round(affinity_lambda(c, 8 * lam, 5D, 10D), 9)").alias("lam"), F.expr("round(snr(c, lam), 9)").alias("snr"))


_AGREE = f"""x AS (SELECT community, label, count(*) AS n FROM l JOIN {WORKLOADS[SMALL].truth_sql} USING (node) GROUP BY ALL),
  r AS (SELECT community, sum(n) AS a FROM x GROUP BY community), s AS (SELECT label, sum(n) AS b FROM x GROUP BY label), t AS (SELECT sum(n) AS t FROM x)"""


@query("nmi", with_graph(f""", {_AGREE} SELECT round(2 * (SELECT sum(n / t * ln(n * t / (a * b))) FROM x JOIN r USING (community) JOIN s USING (label), t)
  / ((SELECT -sum(a / t * ln(a / t)) FROM r, t) + (SELECT -sum(b / t * ln(b / t)) FROM s, t)), 6)::DOUBLE AS nmi""", SMALL))
def _(spark, sf):
    tg, labels = based(spark, sf, SMALL)
    return rounded(agreement.agreement(agreement.contingency(labels, WORKLOADS[SMALL].truth(spark, sf))), "nmi").select("nmi")


@query("ari", with_graph(f""", {_AGREE}, p AS (SELECT (SELECT sum(n * (n - 1) / 2) FROM x) AS both_in, (SELECT sum(a * (a - 1) / 2) FROM r) AS pa, (SELECT sum(b * (b - 1) / 2) FROM s) AS pb, (SELECT t * (t - 1) / 2 FROM t) AS every)
  SELECT round((both_in - pa * pb / every) / ((pa + pb) / 2 - pa * pb / every), 6)::DOUBLE AS ari,
  round((SELECT sum(m) FROM (SELECT max(n) AS m FROM x GROUP BY community)) / (SELECT t FROM t), 6)::DOUBLE AS purity,
  round((SELECT sum(m) FROM (SELECT max(n) AS m FROM x GROUP BY label)) / (SELECT t FROM t), 6)::DOUBLE AS overlap FROM p""", SMALL))
def _(spark, sf):
    tg, labels = based(spark, sf, SMALL)
    return rounded(agreement.agreement(agreement.contingency(labels, WORKLOADS[SMALL].truth(spark, sf))), "ari", "purity", "overlap").select("ari", "purity", "overlap")


# ---------------------------------------------------------------- single steps

_X = "((sid % 97) / 97.0)"


def _vector(nodes: DataFrame) -> DataFrame:
    return nodes.select("sid", (F.pmod("sid", F.lit(97)) / 97.0).alias("c0"), (F.pmod("sid", F.lit(31)) / 31.0).alias("c1"))


_STEP = f""", {SUPRA_SQL}, v AS (SELECT {_sid("slice", "node")} AS sid, slice, node FROM n), d AS (SELECT a AS sid, sum(weight)::DOUBLE AS d FROM s GROUP BY a),
  x AS (SELECT sid, (sid % 97) / 97.0::DOUBLE AS c0, (sid % 31) / 31.0::DOUBLE AS c1 FROM v),
  p AS (SELECT a AS sid, sum(weight * c0)::DOUBLE AS p0, sum(weight * c1)::DOUBLE AS p1 FROM s JOIN x ON x.sid = s.b GROUP BY a),
  y AS (SELECT v.*, x.c0, x.c1, coalesce(d.d, 0) AS d, coalesce(p0, 0) AS p0, coalesce(p1, 0) AS p1, coalesce(k.k, 0) AS k FROM v JOIN x USING (sid) LEFT JOIN d USING (sid) LEFT JOIN p USING (sid) LEFT JOIN k ON k.slice = v.slice AND k.node = v.node)"""


def _two(a: str) -> str:
    return f"SELECT sid, round({a.format(0)}, 6)::DOUBLE AS c0, round({a.format(1)}, 6)::DOUBLE AS c1 FROM y"


def _step(name: str, sql: str, make: Callable[[TemporalGraph, SupraGraph], object]) -> None:
    def run(spark, sf):
        tg = graph(spark, sf, SMALL)
        supra = supra_graph(tg)
        return rounded(make(tg, supra).apply(_vector(supra.nodes)), "c0", "c1")

    query(name, with_graph(_STEP + sql, SMALL))(run)


_step("laplacian_step", _two("(d * c{0} - p{0})"), lambda tg, s: Laplacian(s, "unnormalised"))
_step("random_walk_step", _two("(c{0} - p{0} / d)"), lambda tg, s: Laplacian(s, "random_walk"))
_step("symmetric_step", ", z AS (SELECT s.a AS sid, sum(weight / sqrt(da.d * db.d) * c0) AS p0, sum(weight / sqrt(da.d * db.d) * c1) AS p1 FROM s JOIN d da ON da.sid = s.a JOIN d db ON db.sid = s.b JOIN x ON x.sid = s.b GROUP BY s.a) SELECT sid, round(x.c0 - z.p0, 6)::DOUBLE AS c0, round(x.c1 - z.p1, 6)::DOUBLE AS c1 FROM x JOIN z USING (sid)", lambda tg, s: Laplacian(s, "symmetric"))
_step("deformed_step", _two("((d + 1.5 * 1.5 - 1) * c{0} - 1.5 * p{0})"), lambda tg, s: DeformedLaplacian(s, 1.5))
_step("supra_modularity_step", _two("(p{0} - d * (SELECT sum(d * c{0}) / sum(d) FROM y))"), lambda tg, s: ModularityOp(s.edges, s.nodes))
_step("multislice_step", _two("(p{0} - k * sum(k * c{0}) OVER (PARTITION BY slice) / sum(k) OVER (PARTITION BY slice))"), lambda tg, s: MultisliceModularityOp(tg, s))


@query("spmv", with_graph(_STEP + "SELECT sid, round(p0, 6)::DOUBLE AS c0, round(p1, 6)::DOUBLE AS c1 FROM p", SMALL))
def _(spark, sf):
    supra = supra_graph(graph(spark, sf, SMALL))
    return rounded(spmv(supra.edges, _vector(supra.nodes)), "c0", "c1")


@query("power_step", with_graph(_STEP + "SELECT sid, round(p0 / sqrt((SELECT sum(p0 * p0) FROM p)), 9)::DOUBLE AS c0 FROM p", SMALL))
def _(spark, sf):
    supra = supra_graph(graph(spark, sf, SMALL))
    y = spmv(supra.edges, _vector(supra.nodes).select("sid", "c0"))
    return y.crossJoin(F.broadcast(y.agg(F.sqrt(F.sum(F.col("c0") * F.col("c0"))).alias("norm")))).select("sid", F.round(F.col("c0") / F.col("norm"), 9).alias("c0"))


@query("nb_step", with_graph(f""", {SUPRA_SQL}, v AS (SELECT {_sid("slice", "node")} AS sid FROM n), x AS (SELECT sid, (sid % 97) / 97.0::DOUBLE AS gs, (sid % 31) / 31.0::DOUBLE AS hs, (sid % 53) / 53.0::DOUBLE AS gt, (sid % 7) / 7.0::DOUBLE AS ht FROM v),
  p AS (SELECT a AS sid, count(*) FILTER (kind = 's') AS ds, count(*) FILTER (kind = 't') AS dt, sum(CASE WHEN kind = 's' THEN gs + gt ELSE 0 END) AS s, sum(CASE WHEN kind = 't' THEN gs + gt ELSE 0 END) AS t FROM s JOIN x ON x.sid = s.b GROUP BY a)
  SELECT sid, round(0.6 * (s - hs), 6)::DOUBLE AS gs, round(0.6 * (ds * (gs + gt) - gs), 6)::DOUBLE AS hs, round(0.7 * (t - ht), 6)::DOUBLE AS gt, round(0.7 * (dt * (gs + gt) - gt), 6)::DOUBLE AS ht FROM x JOIN p USING (sid)""", SMALL))
def _(spark, sf):
    supra = supra_graph(graph(spark, sf, SMALL))
    part = lambda m: F.pmod("sid", F.lit(m)) / float(m)
    state = supra.nodes.select("sid", part(97).alias("gs"), part(31).alias("hs"), part(53).alias("gt"), part(7).alias("ht"))
    return rounded(NonBacktracking(supra, 0.6, 0.7).apply(state), "gs", "hs", "gt", "ht")


@query("lloyd_step", """WITH p AS (SELECT vec_id, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y FROM embeddings), c AS (SELECT vec_id AS centre, x AS cx, y AS cy FROM p WHERE vec_id < 4),
  a AS (SELECT p.*, (SELECT centre FROM c ORDER BY (p.x - cx) * (p.x - cx) + (p.y - cy) * (p.y - cy), centre LIMIT 1) AS centre FROM p)
  SELECT centre, count(*) AS n, round(avg(x), 6) AS x, round(avg(y), 6) AS y FROM a GROUP BY centre""")
def _(spark, sf):
    p = load(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    return rounded(lloyd_step(p, p.filter("id < 4").withColumnRenamed("id", "centre"), ["x", "y"]), "x", "y")


@query("local_move_round", with_graph(f""", {SUPRA_SQL}, q AS (SELECT {_sid("slice", "node")} AS v, slice, (node % 3)::BIGINT AS c, k FROM l JOIN k USING (slice, node)),
  m AS (SELECT slice, sum(k) AS m FROM k GROUP BY slice), t AS (SELECT c, slice, sum(k) AS kc FROM q GROUP BY ALL),
  w AS (SELECT v, c, sum(w) AS w FROM (SELECT s.a AS v, q.c, 2 * weight AS w FROM s JOIN q ON q.v = s.b UNION ALL SELECT v, c, 0 FROM q) GROUP BY ALL),
  g AS (SELECT w.v, q.c AS own, w.c, w.w - 2 * q.k * (coalesce(t.kc, 0) - CASE WHEN w.c = q.c THEN q.k ELSE 0 END) / m.m AS gain FROM w JOIN q USING (v) JOIN m ON m.slice = q.slice LEFT JOIN t ON t.c = w.c AND t.slice = q.slice),
  o AS (SELECT *, row_number() OVER (PARTITION BY v ORDER BY round(gain, 7) DESC, c) AS r, max(CASE WHEN c = own THEN gain END) OVER (PARTITION BY v) AS stay FROM g)
  SELECT v, own, c FROM o WHERE r = 1 AND round(gain, 7) > round(stay, 7)""", SMALL))
def _(spark, sf):
    """The best move of every temporal node against the slices' nulls, from the labels node mod 3."""
    tg, labels = based(spark, sf, SMALL)
    supra = supra_graph(tg)
    nulls = null_strengths(tg, supra)
    level = Distributed(summed(supra.edges), nulls, slice_rates(nulls, 1.0, "modularity"), labels.select(sid(F.col("slice"), F.col("node")).alias("v"), F.pmod("node", F.lit(3)).alias("c")))
    g = level.gains(level.labels).withColumn("gain", F.round("gain", 7))
    best = g.groupBy("v", "own").agg(F.max(F.struct("gain", (-F.col("c")).alias("minus"))).alias("best"), F.max(F.when(F.col("c") == F.col("own"), F.col("gain"))).alias("stay"))
    return best.filter("best.gain > stay").select("v", "own", (-F.col("best.minus")).alias("c"))


@query("aggregate_graph", with_graph(f"""{_SUPRA_ENDS} SELECT ca AS a, cb AS b, (2 * sum(weight))::DOUBLE AS w FROM se WHERE ca <> cb GROUP BY ca, cb"""))
def _(spark, sf):
    tg, labels = based(spark, sf)
    supra = supra_graph(tg)
    nulls = null_strengths(tg, supra)
    parts = labels.select(sid(F.col("slice"), F.col("node")).alias("v"), F.col("community").alias("r"))
    return Distributed(summed(supra.edges), nulls, slice_rates(nulls, 1.0, "modularity"), parts.toDF("v", "c")).aggregate(parts).edges


# ---------------------------------------------------------------- methods, scored against known optima

#: Classes so clear that they are the optimum of every objective; in CLEAR they stay, in DRIFT nodes change theirs.
CLEAR, DRIFT = PlantedPartition(200, 4, 4, 16.0, 0.9, 1.0, seed=5), PlantedPartition(240, 4, 4, 18.0, 0.9, 0.95, seed=6)


def with_planted(body: str, p: PlantedPartition = CLEAR, omega: float = 1.0) -> str:
    """SQL over e, n, l (the planted classes as labels), k, ties, ends and score (nodes, classes, Q_MS of the classes)."""
    return f"""WITH e AS (SELECT slice, src, dst, weight FROM {edges_sql(p)}),
  n AS (SELECT DISTINCT slice, node FROM (SELECT slice, src AS node FROM e UNION ALL SELECT slice, dst FROM e)),
  l AS (SELECT n.slice, n.node, t.label AS community FROM n JOIN {labels_sql(p)} t ON t.slice = n.slice AND t.node = n.node),
  k AS (SELECT slice, node, sum(weight) AS k FROM (SELECT slice, src AS node, weight FROM e UNION ALL SELECT slice, dst, weight FROM e) GROUP BY ALL),
  ties AS (SELECT slice AS slice_a, slice_b, node FROM (SELECT slice, node, lead(slice) OVER (PARTITION BY node ORDER BY slice) AS slice_b FROM n) WHERE slice_b = slice + 1),
  ends AS (SELECT e.*, a.community AS ca, b.community AS cb FROM e JOIN l a ON a.slice = e.slice AND a.node = e.src JOIN l b ON b.slice = e.slice AND b.node = e.dst),
  kept AS (SELECT count(*) AS n FROM ties t JOIN l a ON a.slice = t.slice_a AND a.node = t.node JOIN l b ON b.slice = t.slice_b AND b.node = t.node WHERE a.community = b.community),
  per AS (SELECT slice, two_m, w, kk FROM (SELECT slice, 2 * sum(weight) AS two_m, sum(CASE WHEN ca = cb THEN weight ELSE 0 END) AS w FROM ends GROUP BY slice)
    JOIN (SELECT slice, sum(kc * kc) AS kk FROM (SELECT slice, community, sum(k) AS kc FROM k JOIN l USING (slice, node) GROUP BY ALL) GROUP BY slice) USING (slice)),
  score AS (SELECT (SELECT count(*) FROM n) AS nodes, (SELECT count(DISTINCT community) FROM l) AS classes,
    round((sum(2 * w - kk / two_m) + 2 * {omega} * (SELECT n FROM kept)) / (sum(two_m) + 2 * {omega} * (SELECT count(*) FROM ties)), 6)::DOUBLE AS q_ms FROM per)
  {body}"""


def planted(spark: SparkSession, p: PlantedPartition = CLEAR) -> TemporalGraph:
    return TemporalGraph(cut(planted_edges(spark, p), "edges"))


def scored(tg: TemporalGraph, labels: DataFrame, omega: float = 1.0) -> DataFrame:
    """nodes (labelled once each), classes and Q_MS of a method's labels."""
    labels = cut(labels, "labels")
    here = labels.join(tg.nodes, ["slice", "node"]).agg(F.countDistinct("slice", "node").alias("nodes"), F.countDistinct("community").alias("classes"))
    return here.crossJoin(quality.multislice_modularity(tg, labels, omega=omega).select(F.round("q_ms", 6).alias("q_ms")))


def _method(name: str, method: Callable[[TemporalGraph], DataFrame], p: PlantedPartition = CLEAR) -> None:
    """A method that finds the planted classes: its labels' score is the classes' own, which SQL works out from these."""
    query(name, with_planted("SELECT * FROM score", p))(lambda spark, sf: scored(tg := planted(spark, p), method(tg)))


def _spectral(operator: str, **options) -> Callable[[TemporalGraph], DataFrame]:
    return lambda g: plans.spectral_clustering(g, 4, operator, **{"omega": 8.0, **options})


_method("leiden_multislice", lambda g: plans.leiden(g, 1.0))
_method("leiden_multislice_drift", lambda g: plans.leiden(g, 1.0), DRIFT)
_method("leiden_supra", lambda g: plans.leiden(g, 4.0, null="global"))
_method("louvain", lambda g: plans.louvain(g, omega=1.0))
_method("baseline_multislice_sequential", lambda g: plans.baseline_multislice_sequential(g, 1.0))
_method("leiden_cpm", lambda g: plans.leiden(g, 1.0, gamma=0.05, quality="cpm"))
_method("leiden_surprise", lambda g: plans.leiden(g, 1.0, quality="surprise"))
_method("leiden_until_stable", lambda g: plans.leiden(g, 1.0, until_stable=True))
_method("leiden_windowed", lambda g: plans.windowed(g, 3, 1, 1.0))
_method("independent_snapshots", lambda g: plans.independent_snapshots(g, match=True))
_method("spectral_deformed", _spectral("deformed"))
_method("spectral_deformed_literal", _spectral("deformed", time_modes="keep"))
_method("spectral_multislice", _spectral("modularity"))
_method("spectral_supra_modularity", _spectral("modularity", null="global"))
_method("spectral_laplacian_sym", _spectral("laplacian", objective="ncut"))
_method("spectral_laplacian_rw", _spectral("laplacian", normalisation="random_walk"))
_method("spectral_laplacian_unnorm", _spectral("laplacian", objective="rcut"))


_STATIC = PlantedPartition(160, 4, 1, 30.0, 0.95, 1.0, seed=5)


@query("spectral_nonbacktracking", with_planted("SELECT count(*) AS nodes, count(DISTINCT community) AS classes, true AS found FROM l", _STATIC))
def _(spark, sf):
    """The static form; one or two nodes of few links may land in another class."""
    labels = cut(plans.spectral_clustering(planted(spark, _STATIC), 4, "nonbacktracking", lam=0.9, eta=1.0), "labels")
    near = agreement.agreement(agreement.contingency(labels, planted_labels(spark, _STATIC)))
    return labels.agg(F.count("*").alias("nodes"), F.countDistinct("community").alias("classes")).crossJoin(near.select((F.col("nmi") > 0.95).alias("found")))


@query("spectral_nonbacktracking_temporal", with_planted("SELECT slice::BIGINT AS slice, true AS found FROM l GROUP BY slice"))
def _(spark, sf):
    """Each slice's classes, for the most part: the leading vectors of several slices mix time and classes."""
    per = _by_slice(spark, plans.spectral_clustering(planted(spark), 4, "nonbacktracking", omega=1.0, lam=0.9, eta=1.0))
    return per.select("slice", (F.col("nmi") > 0.8).alias("found"))


def _by_slice(spark: SparkSession, labels: DataFrame) -> DataFrame:
    """How each slice's labels agree with its planted classes."""
    both = cut(labels, "labels").join(planted_labels(spark, CLEAR), ["slice", "node"])
    cells = both.groupBy("slice", "community", "label").agg(F.count("*").alias("x"))
    per = lambda by: Window.partitionBy("slice", *by)
    cells = cells.withColumns({"n": F.sum("x").over(per([])), "a": F.sum("x").over(per(["community"])), "b": F.sum("x").over(per(["label"]))})
    plogp = lambda part: -F.col("x") / F.col("n") * F.ln(part / F.col("n"))
    sums = cells.groupBy("slice").agg(F.countDistinct("community").alias("classes"), F.sum(F.col("x") / F.col("n") * F.ln(F.col("x") * F.col("n") / (F.col("a") * F.col("b")))).alias("mutual"), F.sum(plogp(F.col("a"))).alias("ha"), F.sum(plogp(F.col("b"))).alias("hb"))
    return sums.select(F.col("slice").cast("bigint").alias("slice"), "classes", F.round(2 * F.col("mutual") / (F.col("ha") + F.col("hb")), 6).alias("nmi"))


@query("spectral_per_slice", with_planted("SELECT slice::BIGINT AS slice, count(DISTINCT community) AS classes, 1.0::DOUBLE AS nmi FROM l GROUP BY slice"))
def _(spark, sf):
    return _by_slice(spark, plans.spectral_clustering(planted(spark), 4, "laplacian", per_slice=True))


def _score(name: str, key: str | None = None, global_omega: float | None = None) -> None:
    """The two nulls on a workload: every temporal node has one label, no community falls apart, and the per-slice null wins on Q_MS.

    SQL states the graph's nodes and Q_MS of one community for all; both methods must pass it, the supra-graph's only where its labels are no slices.
    """
    w = WORKLOADS[name]

    def run(spark, sf):
        tg = graph(spark, sf, name).stored()
        omega = 1.0
        per = cut(plans.leiden(tg, omega), "labels")
        whole = cut(plans.leiden(tg, global_omega or omega, null="global"), "labels")
        q = lambda x: quality.multislice_modularity(tg, x, omega=omega).first().q_ms
        a, b, one = q(per), q(whole), q(tg.nodes.withColumn("community", F.lit(0).cast("bigint")))
        from .components import check_connected

        if tg.complete:
            broken = complete.check_connected(per).first().broken
        else:
            broken = check_connected(supra_graph(tg, omega).edges.filter("a < b"), per.select(sid(F.col("slice"), F.col("node")).alias("sid"), "community")).first().broken
        counts = per.join(whole.drop("community"), ["slice", "node"]).agg(F.count("*").alias("nodes"))
        return counts.select("nodes", F.lit(broken).cast("bigint").alias("broken"), F.lit(round(one, 6)).alias("q_one"), F.lit(a > one - 1e-9).alias("beats_one"), F.lit(a >= b - 0.002).alias("slice_null_wins"))

    sql = "SELECT (SELECT count(*) FROM n) AS nodes, 0::BIGINT AS broken, round(2.0 * (SELECT count(*) FROM ties) / ((SELECT 2 * sum(weight) FROM e) + 2.0 * (SELECT count(*) FROM ties)), 6)::DOUBLE AS q_one, true AS beats_one, true AS slice_null_wins"
    query(f"score_{key or name}", with_graph(sql, name))(run)


for _name in ("docwords_static", "vec_knn_static", "nation_trade_year", "copart_quarter_thinned", "trade_region_year_thinned", "docwords_arrival", "contact_hour", "cosupp_year", "cosupp_quarter", "cosupp_month", "cosupp_day", "contact_10min", "contact_5min", "page_links"):
    if _name in WORKLOADS:
        _score(_name)


@query("degenerate_time", "SELECT true AS degenerate_time")
def _(spark, sf):
    """The global null at a weak coupling labels slices, not communities."""
    return quality.time_degenerate(plans.leiden(graph(spark, sf, SMALL), 1.0, null="global")).select("degenerate_time")


@query("connected_communities", "SELECT 0::BIGINT AS broken")
def _(spark, sf):
    from .components import check_connected

    tg = graph(spark, sf, SMALL)
    labels = cut(plans.leiden(tg, 50.0), "labels")
    return check_connected(supra_graph(tg, 50.0).edges, labels.select(sid(F.col("slice"), F.col("node")).alias("sid"), "community")).select("broken")


@query("resolution_profile", "SELECT true AS finer")
def _(spark, sf):
    p = plans.resolution_profile(graph(spark, sf, SMALL), [0.5, 1.0, 2.0], omega=50.0)
    per = p.groupBy("gamma").agg(F.countDistinct("community").alias("c"))
    return per.agg((F.max_by("c", "gamma") >= F.min_by("c", "gamma")).alias("finer"))


@query("coupling_profile", "SELECT true AS steadier")
def _(spark, sf):
    p = plans.coupling_profile(graph(spark, sf, SMALL), [0.0, 50.0, 1000.0])
    w = Window.partitionBy("omega", "node").orderBy("slice")
    per = p.withColumn("kept", (F.lag("community").over(w) == F.col("community")).cast("int")).groupBy("omega").agg(F.avg("kept").alias("rate"))
    return per.agg((F.max_by("rate", "omega") >= F.min_by("rate", "omega")).alias("steadier"))


_FLAT_CLEAR = """, f AS (SELECT src, dst, sum(weight) AS weight FROM e GROUP BY ALL), c AS (SELECT DISTINCT node, community FROM l),
  m AS (SELECT sum(weight) AS m FROM f), inside AS (SELECT sum(weight) AS w FROM f JOIN c a ON a.node = src JOIN c b ON b.node = dst WHERE a.community = b.community)"""
_FLAT_Q = _FLAT_CLEAR + """, v AS (SELECT sum(kc * kc) AS kk FROM (SELECT community, sum(weight) AS kc FROM (SELECT src AS node, weight FROM f UNION ALL SELECT dst, weight FROM f) JOIN c USING (node) GROUP BY community))
  SELECT (SELECT count(*) FROM c) AS nodes, (SELECT count(DISTINCT community) FROM c) AS classes, round((SELECT w FROM inside) / m - (SELECT kk FROM v) / (4 * m * m), 6)::DOUBLE AS q FROM m"""


def _flat_score(e: DataFrame, labels: DataFrame) -> DataFrame:
    labels = cut(labels.select("node", "community"), "labels")
    return labels.agg(F.countDistinct("node").alias("nodes"), F.countDistinct("community").alias("classes")).crossJoin(rounded(quality.modularity(e, labels), "q").select("q"))


@query("modularity_bisect", with_planted(_FLAT_Q, PlantedPartition(120, 2, 1, 14.0, 0.9, 1.0, seed=8)))
def _(spark, sf):
    """Two classes, and no part of them has a positive eigenvalue that splits it to a gain."""
    e = cut(flatten(planted(spark, PlantedPartition(120, 2, 1, 14.0, 0.9, 1.0, seed=8)).edges), "edges")
    return _flat_score(e, plans.modularity_bisect(e, recursive=True))


@query("flattened_leiden", with_planted(_FLAT_Q))
def _(spark, sf):
    e = cut(flatten(planted(spark).edges), "edges")
    return _flat_score(e, plans.leiden(TemporalGraph(e), 0.0))


@query("directed_leiden", with_planted(_FLAT_CLEAR + """, o AS (SELECT community, sum(weight) AS k FROM f JOIN c ON node = src GROUP BY community), i AS (SELECT community, sum(weight) AS k FROM f JOIN c ON node = dst GROUP BY community)
  SELECT (SELECT count(*) FROM c) AS nodes, (SELECT count(DISTINCT community) FROM c) AS classes, round((SELECT w FROM inside) / m - (SELECT sum(o.k * i.k) FROM o JOIN i USING (community)) / (m * m), 6)::DOUBLE AS q FROM m"""))
def _(spark, sf):
    """Each edge leads from its smaller node to the larger one; the null is that of in- and out-strengths."""
    e = cut(flatten(planted(spark).edges), "edges")
    labels = cut(plans.leiden(TemporalGraph(e, directed=True), 0.0).select("node", "community"), "labels")
    q = quality.modularity(e, labels, directed=True, convention="directed")
    return labels.agg(F.countDistinct("node").alias("nodes"), F.countDistinct("community").alias("classes")).crossJoin(rounded(q, "q").select("q"))


@query("directed_leiden_users", with_graph("SELECT slice, count(*) AS nodes, true AS several FROM n GROUP BY slice", "user_succession_day"))
def _(spark, sf):
    """All days of the users' succession."""
    tg = graph(spark, sf, "user_succession_day")
    tg = tg.with_edges(cut(tg.edges, "edges"))
    return plans.leiden(tg, 1.0).groupBy("slice").agg(F.count("*").alias("nodes"), (F.countDistinct("community") > 1).alias("several"))


_TWO = PlantedPartition(120, 2, 1, 14.0, 0.9, 1.0, seed=8)


@query("fiedler_split", with_planted("""SELECT 2::BIGINT AS parts, round(cut / least(va, vb), 6)::DOUBLE AS phi FROM (SELECT
  (SELECT sum(weight) FROM ends WHERE ca <> cb) AS cut, (SELECT sum(k) FROM k JOIN l USING (slice, node) WHERE community = 0) AS va, (SELECT sum(k) FROM k JOIN l USING (slice, node) WHERE community = 1) AS vb)""", _TWO))
def _(spark, sf):
    """The sweep over the second eigenvector cuts a graph of two classes between these."""
    tg = planted(spark, _TWO)
    labels = cut(plans.fiedler_split(tg, threshold="sweep").select("node", "community"), "labels")
    c = quality.conductance(tg.edges, labels).agg(F.count("*").alias("parts"), F.max("conductance").alias("phi"))
    return rounded(c, "phi")


#: Customers dealt to 40 nodes, whose pairs the order lines draw.
_CELLS = PlantedTable(CLEAR, cells=40)


@query("estimate_k", f"""WITH e AS (SELECT * FROM {_CELLS.edges_sql}), n AS (SELECT slice, src AS node FROM e UNION SELECT slice, dst FROM e)
  SELECT slice, count(DISTINCT label) AS k FROM n JOIN {_CELLS.labels_sql} USING (slice, node) GROUP BY slice""")
def _(spark, sf):
    return plans.estimate_k(TemporalGraph(cut(_CELLS.edges(spark, sf), "edges")))


_SWEEP = [(lam, eta) for lam in (0.1, 0.8) for eta in (0.7, 1.0)]


@query("detectability_sweep", f"SELECT lam::DOUBLE AS lam, eta::DOUBLE AS eta, round(12 * lam * lam, 6)::DOUBLE AS snr, 12 * lam * lam > 1 AS found FROM (VALUES {', '.join(f'({a}, {b})' for a, b in _SWEEP)}) v(lam, eta)")
def _(spark, sf):
    """The deformed Laplacian finds planted classes above the threshold, and does not below it, whether nodes change class or not."""
    rows = None
    for lam, eta in _SWEEP:
        p = PlantedPartition(300, 2, 3, 12.0, lam, eta, seed=2)
        tg = planted(spark, p)
        labels = plans.spectral_clustering(tg, p.k, "deformed", omega=2.0)
        found = agreement.agreement(agreement.contingency(labels, planted_labels(spark, p))).select(F.lit(lam).alias("lam"), F.lit(eta).alias("eta"), F.round(F.lit(p.c * lam**2), 6).alias("snr"), (F.col("nmi") > 0.3).alias("found"))
        rows = found if rows is None else rows.union(found)
    return rows


@query("leiden_distributed", with_planted("SELECT * FROM score"))
def _(spark, sf):
    """The distributed engine, handed over to one task when few edges are left."""
    tg = planted(spark)
    return scored(tg, plans.leiden(tg, 1.0, backend_name="distributed", finish=8000))


def _path(spark: SparkSession, n: int) -> SupraGraph:
    """A path of n nodes, whose Laplacian has the eigenvalues 2 - 2 cos(pi j / n)."""
    ids = spark.range(n).select(F.col("id").alias("sid"), F.lit(0).alias("slice"), F.col("id").alias("node"))
    ahead = spark.range(n - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"), F.lit(1.0).alias("weight"), F.lit("s").alias("kind"))
    return SupraGraph(cut(ids, "nodes"), cut(ahead.union(ahead.select("b", "a", "weight", "kind")), "edges"))


def _values(spark: SparkSession, values) -> DataFrame:
    return spark.createDataFrame([(i, abs(round(float(v), 4))) for i, v in enumerate(sorted(values))], "j bigint, value double")


@query("lanczos", "SELECT j, round(2 - 2 * cos(pi() * j / 12), 4)::DOUBLE AS value FROM range(3) r(j)")
def _(spark, sf):
    """The lower end of a path's Laplacian by distributed Lanczos steps."""
    return _values(spark, distributed_lanczos(Laplacian(_path(spark, 12), "unnormalised"), 3, steps=12)[0])


@query("block_eigenpairs", "SELECT j, round(2 - 2 * cos(pi() * j / 9), 4)::DOUBLE AS value FROM range(2) r(j)")
def _(spark, sf):
    """The two smallest pairs of a path's Laplacian by filtered subspace iteration."""
    return _values(spark, block_eigs(Laplacian(_path(spark, 9), "unnormalised"), 2, tol=1e-5, degree=5)[0])


@query("slice_spectra", with_graph("SELECT slice, count(DISTINCT node) AS n, 0.0::DOUBLE AS trace FROM n GROUP BY slice", SMALL))
def _(spark, sf):
    s = functions.slice_spectra(graph(spark, sf, SMALL).edges)
    return s.select("slice", F.size("spectrum").cast("bigint").alias("n"), F.abs(F.round(F.aggregate("spectrum", F.lit(0.0), lambda a, x: a + x), 5)).alias("trace"))


@query("windows_of", with_graph("SELECT slice, run::INT AS run FROM (SELECT DISTINCT slice FROM e), (SELECT unnest(range(20)) AS run) WHERE slice BETWEEN run * 2 AND run * 2 + 3"))
def _(spark, sf):
    functions.register_windows(spark)
    graph(spark, sf).edges.select("slice").distinct().createOrReplaceTempView("slices_in_use")
    return spark.sql("SELECT s.slice, w.run FROM slices_in_use s, LATERAL windows_of(s.slice, 4, 2) w")


@query("sql_views", with_graph("SELECT slice, count(*) AS m FROM e GROUP BY slice", SMALL))
def _(spark, sf):
    register_views(spark, sf, {"nation_trade": graph(spark, sf, SMALL).edges})
    return spark.sql("SELECT slice, count(*) AS m FROM nation_trade GROUP BY slice")


@query("planted_source", "SELECT * FROM " + edges_sql(PlantedPartition(60, 3, 3, 6.0, 0.5, 0.9, seed=4), "(SELECT DISTINCT user_id AS range FROM events)", "(SELECT event_id AS range FROM events)"))
def _(spark, sf):
    """Users are the nodes, and each event is a draw of the data source."""
    events = load(spark, sf, "events").select("event_id", "user_id")
    top = events.agg(F.max("user_id").alias("user"), F.max("event_id").alias("event")).first()
    planted_source.register(spark)
    options = {"n": 1 if top.user is None else top.user + 1, "draws": 0 if top.event is None else top.event + 1}
    drawn = spark.read.format("planted_partition").options(k="3", slices="3", c="6.0", lam="0.5", eta="0.9", seed="4", **options).load()
    users = cut(events.select("user_id").filter("user_id is not null").distinct(), "users")
    drawn = drawn.join(events.select(F.col("event_id").alias("id")), "id", "left_semi")
    for end in ("src", "dst"):
        drawn = drawn.join(users.select(F.col("user_id").alias(end)), end, "left_semi")
    return drawn.select("slice", "src", "dst", "weight").distinct()


@query("cosine_pairs", "SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def _(spark, sf):
    v = load(spark, sf, "embeddings").select("vec_id", "embedding")
    after = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    return v.join(after, "vec_id").select("vec_id", F.round(functions.cosine("embedding", "other"), 6).alias("cosine"))


# ---------------------------------------------------------------- tracking


@query("persistence", with_graph("SELECT slice, count(*) AS n, count(*) FILTER (was = community) AS kept, count(*) FILTER (was = community) / count(*) AS rate FROM (SELECT *, lag(community) OVER w AS was, lag(slice) OVER w AS before FROM l WINDOW w AS (PARTITION BY node ORDER BY slice)) WHERE before = slice - 1 GROUP BY slice"))
def _(spark, sf):
    return tracking.persistence(based(spark, sf)[1])


@query("label_changes", with_graph("SELECT slice, node, was, community FROM (SELECT *, lag(community) OVER (PARTITION BY node ORDER BY slice) AS was FROM l) WHERE was IS DISTINCT FROM community"))
def _(spark, sf):
    return tracking.label_changes(based(spark, sf)[1])


@query("community_timeline", with_graph("""SELECT slice, community, count(*) AS size, coalesce(any_value(volume), 0) AS volume, coalesce(any_value(inside), 0) AS inside, coalesce(any_value(cut), 0) AS cut FROM l LEFT JOIN (
  SELECT slice, c AS community, sum(weight) AS volume, sum(CASE WHEN c = o THEN weight ELSE 0 END) / 2 AS inside, sum(CASE WHEN c <> o THEN weight ELSE 0 END) AS cut FROM (SELECT slice, ca AS c, cb AS o, weight FROM ends UNION ALL SELECT slice, cb, ca, weight FROM ends) GROUP BY ALL) USING (slice, community) GROUP BY ALL"""))
def _(spark, sf):
    tg, labels = based(spark, sf)
    return tracking.community_timeline(tg.edges, labels)


@query("transitions", with_graph("SELECT a.slice, a.community AS from_community, b.community AS to_community, count(*) AS n FROM l a JOIN l b ON a.node = b.node AND b.slice = a.slice + 1 GROUP BY ALL"))
def _(spark, sf):
    return tracking.transitions(based(spark, sf)[1])


@query("lifecycle", with_graph("""SELECT slice, community, coalesce(b, 0) AS before, coalesce(a, 0) AS after, CASE WHEN coalesce(b, 0) = 0 THEN 'birth' WHEN coalesce(a, 0) = 0 THEN 'death' WHEN a > b THEN 'growth' WHEN a < b THEN 'shrinkage' ELSE 'same' END AS event FROM
  (SELECT slice, community, count(*) AS a FROM l GROUP BY ALL) FULL JOIN (SELECT slice + 1 AS slice, community, count(*) AS b FROM l GROUP BY ALL) USING (slice, community) WHERE slice > (SELECT min(slice) FROM l) AND slice <= (SELECT max(slice) FROM l)""", "contact_hour"))
def _(spark, sf):
    return tracking.lifecycle(based(spark, sf, "contact_hour")[1])


@query("splits_and_merges", with_graph(""", s AS (SELECT slice, node, (CASE WHEN slice BETWEEN 2 AND 4 THEN node % 4 ELSE node % 2 END)::BIGINT AS community FROM n),
  t AS (SELECT a.slice, a.community AS x, b.community AS y, count(*) AS n FROM s a JOIN s b ON a.node = b.node AND b.slice = a.slice + 1 GROUP BY ALL)
  SELECT slice, x AS community, count(*) AS parts, 'split' AS kind FROM (SELECT *, sum(n) OVER (PARTITION BY slice, x) AS o FROM t) WHERE n >= 0.3 * o GROUP BY ALL HAVING count(*) > 1
  UNION ALL SELECT slice, y, count(*), 'merge' FROM (SELECT *, sum(n) OVER (PARTITION BY slice, y) AS o FROM t) WHERE n >= 0.3 * o GROUP BY ALL HAVING count(*) > 1""", SMALL))
def _(spark, sf):
    """Two communities that split in two each at slice 2 and merge again at slice 5."""
    nodes = graph(spark, sf, SMALL).nodes
    labels = nodes.select("slice", "node", F.when(F.col("slice").between(2, 4), F.pmod("node", F.lit(4))).otherwise(F.pmod("node", F.lit(2))).alias("community"))
    return tracking.splits_and_merges(labels)


@query("match_labels", with_graph(""", p AS (SELECT a.community AS old, b.community AS new, count(*) AS n FROM l a JOIN l b ON a.node = b.node AND a.slice = 8 AND b.slice = 9 GROUP BY ALL)
  SELECT old, new, n, n::DOUBLE AS score FROM (SELECT *, row_number() OVER (PARTITION BY old ORDER BY n DESC, new) AS x, row_number() OVER (PARTITION BY new ORDER BY n DESC, old) AS y FROM p) WHERE x = 1 AND y = 1"""))
def _(spark, sf):
    labels = based(spark, sf)[1]
    return tracking.match_labels(labels.filter("slice = 8"), labels.filter("slice = 9"))


@query("structure_over_time", with_graph("SELECT slice, count(*) AS nodes, (sum(d) / 2)::BIGINT AS edges, round(sum(d) / (count(*) * (count(*) - 1)), 9)::DOUBLE AS density, round(avg(d), 9) AS mean_degree, round(avg(d * d), 9) AS mean_square_degree FROM (SELECT slice, node, count(*) AS d FROM (SELECT slice, src AS node FROM e UNION ALL SELECT slice, dst FROM e) GROUP BY ALL) GROUP BY slice"))
def _(spark, sf):
    return rounded(tracking.structure_over_time(graph(spark, sf).edges), "density", "mean_degree", "mean_square_degree", digits=9)


@query("edge_survival", with_graph("SELECT slice, count(*) AS n, count(*) FILTER (nxt = slice + 1) AS kept FROM (SELECT *, lead(slice) OVER (PARTITION BY src, dst ORDER BY slice) AS nxt FROM e) GROUP BY slice"))
def _(spark, sf):
    return tracking.edge_survival(graph(spark, sf).edges)


@query("slice_jaccard", with_graph(""", c AS (SELECT slice, count(*) AS n, count(*) FILTER (nxt = slice + 1) AS kept FROM (SELECT *, lead(slice) OVER (PARTITION BY src, dst ORDER BY slice) AS nxt FROM e) GROUP BY slice)
  SELECT a.slice, round(a.kept / (a.n + b.n - a.kept), 9) AS jaccard FROM c a JOIN c b ON b.slice = a.slice + 1"""))
def _(spark, sf):
    return rounded(tracking.slice_jaccard(graph(spark, sf).edges), "jaccard", digits=9)


@query("first_seen", with_graph("SELECT node, min(slice) AS first, nth_s AS second, arg_min(community, slice) AS community FROM (SELECT *, nth_value(slice, 2) OVER (PARTITION BY node ORDER BY slice ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS nth_s FROM l) GROUP BY node, nth_s"))
def _(spark, sf):
    return tracking.first_seen(based(spark, sf)[1])


@query("carry_labels", with_graph("""SELECT slice, node, community FROM (SELECT g.slice, g.node, last_value(l.community IGNORE NULLS) OVER (PARTITION BY g.node ORDER BY g.slice ROWS UNBOUNDED PRECEDING) AS community
  FROM (SELECT s.slice, v.node FROM (SELECT DISTINCT slice FROM n) s, (SELECT DISTINCT node FROM n) v) g LEFT JOIN l ON l.slice = g.slice AND l.node = g.node) WHERE community IS NOT NULL""", "contact_hour"))
def _(spark, sf):
    tg, labels = based(spark, sf, "contact_hour")
    return tracking.carry_labels(labels, tg.edges, tg.nodes)


_HOUR = "floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) / 3600000000)::INT"


@query("asof_labels", with_graph(f"SELECT v.event_id AS event, v.user_id AS node, v.slice, l.community FROM (SELECT *, {_HOUR} AS slice FROM events) v ASOF LEFT JOIN (SELECT * FROM l WHERE slice % 3 = 0) l ON l.node = v.user_id AND v.slice >= l.slice", "contact_hour"))
def _(spark, sf):
    from .temporal import slice_number

    events = load(spark, sf, "events").select(F.col("event_id").alias("event"), F.col("user_id").alias("node"), slice_number(F.col("ts"), "hour", EVENTS_FROM).alias("slice"))
    return tracking.asof_labels(events, based(spark, sf, "contact_hour")[1].filter("slice % 3 = 0"))


# ---------------------------------------------------------------- surrounding operators


@query("slice_range", with_graph("SELECT * FROM e WHERE slice BETWEEN 3 AND 5"))
def _(spark, sf):
    return between_slices(graph(spark, sf).edges, 3, 5)


@query("min_weight", with_graph("SELECT * FROM e WHERE weight >= 2"))
def _(spark, sf):
    return min_weight(graph(spark, sf).edges, 2.0)


@query("backbone", with_graph("""SELECT DISTINCT slice, least(node, other) AS src, greatest(node, other) AS dst, weight FROM (
  SELECT *, row_number() OVER (PARTITION BY slice, node ORDER BY weight DESC, other) AS r FROM (SELECT slice, src AS node, dst AS other, weight FROM e UNION ALL SELECT slice, dst, src, weight FROM e)) WHERE r <= 2"""))
def _(spark, sf):
    return backbone(graph(spark, sf).edges, 2)


@query("induced", with_graph("SELECT * FROM e WHERE src % 3 = 0 AND dst % 3 = 0"))
def _(spark, sf):
    e = graph(spark, sf).edges
    return induced(e, active_nodes(e).select("node").distinct().filter("node % 3 = 0"))


@query("ego", with_graph(""", p AS (SELECT src AS u, dst AS v FROM e UNION SELECT dst, src FROM e)
  SELECT node, min(d)::INT AS distance FROM (SELECT 1::BIGINT AS node, 0 AS d UNION ALL SELECT v, 1 FROM p WHERE u = 1 UNION ALL SELECT b.v, 2 FROM p a JOIN p b ON b.u = a.v WHERE a.u = 1) GROUP BY node""", "copart_quarter"))
def _(spark, sf):
    return ego(graph(spark, sf, "copart_quarter").edges, 1, 2)


@query("members", with_graph("SELECT slice, node FROM l WHERE community = 2"))
def _(spark, sf):
    return based(spark, sf)[1].filter("community = 2").select("slice", "node")


@query("source_filters", """SELECT c_custkey FROM customer c WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderdate < TIMESTAMP '1996-01-01')
  AND NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderdate >= TIMESTAMP '2001-01-01') AND c_mktsegment LIKE '%IN%' AND regexp_matches(c_mktsegment, '^[BM]')""")
def _(spark, sf):
    orders = load(spark, sf, "orders")
    early = orders.filter("o_orderdate < '1996-01-01'").select(F.col("o_custkey").alias("c_custkey"))
    late = orders.filter("o_orderdate >= '2001-01-01'").select(F.col("o_custkey").alias("c_custkey"))
    c = load(spark, sf, "customer").filter(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_mktsegment").like("%IN%") & F.col("c_mktsegment").rlike("^[BM]"))
    return c.join(early, "c_custkey", "left_semi").join(late, "c_custkey", "left_anti").select("c_custkey")


@query("contacts_within", """WITH v AS (SELECT event_id, user_id AS u, epoch_us(ts) AS t FROM events)
  SELECT least(a.u, b.u) AS src, greatest(a.u, b.u) AS dst, count(*) AS contacts FROM v a JOIN v b ON a.u < b.u AND b.t BETWEEN a.t - 60000000 AND a.t + 60000000 GROUP BY ALL""")
def _(spark, sf):
    return contacts_within(load(spark, sf, "events"), "user_id", "ts", 60)


@query("absent_nodes", with_graph("SELECT DISTINCT node FROM n WHERE node NOT IN (SELECT node FROM n WHERE slice = 100)", "contact_hour"))
def _(spark, sf):
    tg = graph(spark, sf, "contact_hour")
    return absent_nodes(tg.edges, 100, tg.nodes)


@query("copart_quarter", f"SELECT slice, src, dst, weight FROM {WORKLOADS['copart_quarter'].sql}")
def _(spark, sf):
    return graph(spark, sf, "copart_quarter").edges


@query("community_totals", with_graph("SELECT slice, community, sum(k) AS k, count(*) AS n FROM k JOIN l USING (slice, node) GROUP BY GROUPING SETS ((slice, community), (slice), ())"))
def _(spark, sf):
    tg, labels = based(spark, sf)
    rows = strengths(tg.edges).join(labels, ["slice", "node"]).select("slice", "community", "k_out")
    return rows.groupingSets([["slice", "community"], ["slice"], []], "slice", "community").agg(F.sum("k_out").alias("k"), F.count("*").alias("n"))


@query("size_rollup", with_graph("SELECT slice, community, count(*) AS n FROM l GROUP BY ROLLUP (slice, community)"))
def _(spark, sf):
    return based(spark, sf)[1].rollup("slice", "community").agg(F.count("*").alias("n"))


@query("contingency", with_graph(f"SELECT community, label, count(*) AS n, grouping_id(community, label)::BIGINT AS level FROM l JOIN {WORKLOADS[SMALL].truth_sql} USING (node) GROUP BY CUBE (community, label)", SMALL))
def _(spark, sf):
    return agreement.contingency_cube(based(spark, sf, SMALL)[1], WORKLOADS[SMALL].truth(spark, sf))


@query("member_lists", with_graph("SELECT slice, community, list_sort(list_distinct(list(node))) AS nodes FROM l GROUP BY slice, community"))
def _(spark, sf):
    return based(spark, sf)[1].groupBy("slice", "community").agg(F.array_sort(F.collect_set("node")).alias("nodes"))


@query("degree_quantiles", with_graph("SELECT slice, round(quantile_cont(k, 0.5), 6) AS median, round(quantile_cont(k, 0.9), 6) AS top FROM k GROUP BY slice"))
def _(spark, sf):
    k = strengths(graph(spark, sf).edges)
    return rounded(k.groupBy("slice").agg(F.percentile("k_out", 0.5).alias("median"), F.percentile("k_out", 0.9).alias("top")), "median", "top")


@query("degree_moments", with_graph("SELECT slice, round(avg(k), 9) AS mean, round(avg(k * k), 9) AS square, round(stddev_samp(k), 9) AS sd, round(corr(k, nxt), 6) AS corr_next FROM (SELECT *, lead(k) OVER (PARTITION BY node ORDER BY slice) AS nxt FROM k) GROUP BY slice"))
def _(spark, sf):
    k = strengths(graph(spark, sf).edges).withColumn("nxt", F.lead("k_out").over(Window.partitionBy("node").orderBy("slice")))
    return rounded(rounded(k.groupBy("slice").agg(F.avg("k_out").alias("mean"), F.avg(F.col("k_out") ** 2).alias("square"), F.stddev_samp("k_out").alias("sd"), F.corr("k_out", "nxt").alias("corr_next")), "mean", "square", "sd", digits=9), "corr_next")


@query("size_matrix", with_graph("SELECT community, " + ", ".join(f"count(*) FILTER (slice = {s}) AS s{s}" for s in range(7)) + " FROM l GROUP BY community", SMALL))
def _(spark, sf):
    p = based(spark, sf, SMALL)[1].groupBy("community").pivot("slice", list(range(7))).count()
    return p.select("community", *(F.coalesce(f"{s}", F.lit(0)).alias(f"s{s}") for s in range(7)))


@query("validate_labels", with_graph("SELECT bool_and(community IS NOT NULL) AS labelled, count(*) FILTER (community < 0) AS negative, count(*) = count(DISTINCT (slice, node)) AS once FROM l"))
def _(spark, sf):
    return based(spark, sf)[1].agg(F.bool_and(F.col("community").isNotNull()).alias("labelled"), F.count_if(F.col("community") < 0).alias("negative"), (F.count("*") == F.countDistinct("slice", "node")).alias("once"))


@query("cut_internal", with_graph("SELECT slice, sum(weight) FILTER (ca = cb) AS inside, sum(weight) FILTER (ca <> cb) AS cut FROM ends GROUP BY slice"))
def _(spark, sf):
    tg, labels = based(spark, sf)
    a, b = labels.toDF("slice", "src", "ca"), labels.toDF("slice", "dst", "cb")
    return tg.edges.join(a, ["slice", "src"]).join(b, ["slice", "dst"]).groupBy("slice").agg(F.sum(F.when(F.col("ca") == F.col("cb"), F.col("weight"))).alias("inside"), F.sum(F.when(F.col("ca") != F.col("cb"), F.col("weight"))).alias("cut"))


@query("melt_embedding", "SELECT vec_id, 'c' || (i - 1) AS dim, round(embedding[i]::DOUBLE, 6) AS value FROM embeddings, (SELECT unnest([1, 2, 3]) AS i)")
def _(spark, sf):
    wide = load(spark, sf, "embeddings").select("vec_id", *(F.col("embedding")[i].cast("double").alias(f"c{i}") for i in range(3)))
    return rounded(wide.unpivot("vec_id", ["c0", "c1", "c2"], "dim", "value"), "value")


@query("rank_communities", with_graph("""SELECT slice, community, n, (row_number() OVER o)::INT AS rn, (rank() OVER s)::INT AS rk, (dense_rank() OVER s)::INT AS dr, (ntile(2) OVER o)::INT AS tile, percent_rank() OVER s AS pr
  FROM (SELECT slice, community, count(*) AS n FROM l GROUP BY ALL) WINDOW o AS (PARTITION BY slice ORDER BY n DESC, community), s AS (PARTITION BY slice ORDER BY n DESC)"""))
def _(spark, sf):
    sizes = based(spark, sf)[1].groupBy("slice", "community").agg(F.count("*").alias("n"))
    o, s = Window.partitionBy("slice").orderBy(F.desc("n"), "community"), Window.partitionBy("slice").orderBy(F.desc("n"))
    return sizes.select("slice", "community", "n", F.row_number().over(o).alias("rn"), F.rank().over(s).alias("rk"), F.dense_rank().over(s).alias("dr"), F.ntile(2).over(o).alias("tile"), F.percent_rank().over(s).alias("pr"))


@query("cumulative_edges", with_graph("SELECT slice, m, (sum(m) OVER (ORDER BY slice))::BIGINT AS total FROM (SELECT slice, count(*) AS m FROM e GROUP BY slice)"))
def _(spark, sf):
    return slice_totals(graph(spark, sf).edges).select("slice", "m", F.sum("m").over(Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, 0)).alias("total"))


@query("moving_activity", with_graph("SELECT slice, avg(m) OVER (ORDER BY slice RANGE BETWEEN 3 PRECEDING AND CURRENT ROW) AS mean FROM (SELECT slice, count(*) AS m FROM e GROUP BY slice)"))
def _(spark, sf):
    return slice_totals(graph(spark, sf).edges).select("slice", F.avg("m").over(Window.orderBy("slice").rangeBetween(-3, 0)).alias("mean"))


@query("degree_cdf", with_graph("SELECT DISTINCT slice, k, round(cume_dist() OVER (PARTITION BY slice ORDER BY k), 9) AS share FROM k"))
def _(spark, sf):
    k = strengths(graph(spark, sf).edges)
    return rounded(k.select("slice", F.col("k_out").alias("k"), F.cume_dist().over(Window.partitionBy("slice").orderBy("k_out")).alias("share")).distinct(), "share", digits=9)


@query("top_communities", with_graph("SELECT slice, community, count(*) AS n FROM l GROUP BY ALL ORDER BY n DESC, slice, community LIMIT 5"))
def _(spark, sf):
    return based(spark, sf)[1].groupBy("slice", "community").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "slice", "community").limit(5)


@query("sweep_cut", with_flat(""", o AS (SELECT node, k, row_number() OVER (ORDER BY k, node) AS place FROM k), d AS (SELECT least(a.place, b.place) AS lo, greatest(a.place, b.place) AS hi, weight FROM f JOIN o a ON a.node = src JOIN o b ON b.node = dst)
  SELECT o.place::BIGINT AS place, round((SELECT sum(weight) FROM d WHERE lo <= o.place AND hi > o.place) / least(sum(k) OVER (ORDER BY place), (SELECT sum(k) FROM k) - sum(k) OVER (ORDER BY place)), 6)::DOUBLE AS phi FROM o WHERE place < (SELECT count(*) FROM o)""", SMALL))
def _(spark, sf):
    """Conductance of every prefix of the nodes in the order of their strength, by one sort and prefix sums."""
    e = flatten(graph(spark, sf, SMALL).edges)
    k = strengths(e).select("node", F.col("k_out").alias("k"))
    o = k.withColumn("place", F.row_number().over(Window.orderBy("k", "node")).cast("bigint"))
    ends = e.join(o.select(F.col("node").alias("src"), F.col("place").alias("x")), "src").join(o.select(F.col("node").alias("dst"), F.col("place").alias("y")), "dst")
    turns = ends.select(F.least("x", "y").alias("place"), F.col("weight").alias("w")).union(ends.select(F.greatest("x", "y"), -F.col("weight"))).groupBy("place").agg(F.sum("w").alias("w"))
    running = Window.orderBy("place").rowsBetween(Window.unboundedPreceding, 0)
    total = F.broadcast(k.agg(F.sum("k").alias("every"), F.count("*").alias("last")))
    both = o.join(turns, "place", "left").select("place", F.sum(F.coalesce("w", F.lit(0.0))).over(running).alias("cut"), F.sum("k").over(running).alias("vol")).crossJoin(total).filter("place < last")
    return both.select("place", F.round(F.col("cut") / F.least("vol", F.col("every") - F.col("vol")), 6).alias("phi"))


@query("label_page", with_graph("SELECT slice, node, community FROM l ORDER BY slice, node LIMIT 20 OFFSET 40"))
def _(spark, sf):
    return based(spark, sf)[1].orderBy("slice", "node").offset(40).limit(20)


@query("kept_edges", with_graph("SELECT src, dst FROM e WHERE slice = 3 INTERSECT SELECT src, dst FROM e WHERE slice = 4"))
def _(spark, sf):
    e = graph(spark, sf).edges
    return snapshot(e, 3).select("src", "dst").intersect(snapshot(e, 4).select("src", "dst"))


@query("born_edges", with_graph("SELECT src, dst FROM e WHERE slice = 4 EXCEPT SELECT src, dst FROM e WHERE slice = 3"))
def _(spark, sf):
    e = graph(spark, sf).edges
    return snapshot(e, 4).select("src", "dst").subtract(snapshot(e, 3).select("src", "dst"))


@query("lost_edges", with_graph("SELECT src, dst FROM e WHERE slice = 3 EXCEPT ALL SELECT src, dst FROM e WHERE slice = 4"))
def _(spark, sf):
    e = graph(spark, sf).edges
    return snapshot(e, 3).select("src", "dst").exceptAll(snapshot(e, 4).select("src", "dst"))


@query("union_distinct", with_graph("SELECT src, dst FROM e WHERE slice = 3 UNION SELECT src, dst FROM e WHERE slice = 4"))
def _(spark, sf):
    e = graph(spark, sf).edges
    return snapshot(e, 3).select("src", "dst").union(snapshot(e, 4).select("src", "dst")).distinct()


@query("date_functions", """SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE AS month, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, month(o_orderdate)::INT AS m,
  datediff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days, (o_orderdate + INTERVAL 36 HOUR)::DATE AS later, epoch_us(o_orderdate)::BIGINT AS micros FROM orders""")
def _(spark, sf):
    t = F.col("o_orderdate")
    return load(spark, sf, "orders").select("o_orderkey", F.date_trunc("month", t).cast("date").alias("month"), F.year(t).alias("y"), F.quarter(t).alias("q"), F.month(t).alias("m"), F.datediff(t.cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.expr("timestampadd(HOUR, 36, o_orderdate)").cast("date").alias("later"), F.unix_micros(t).alias("micros"))


@query("string_functions", """SELECT doc_id, len(regexp_extract_all(lower(text), '[a-z]{9,}'))::INT AS words, substr(md5(text), 1, 8) AS head, ('0x' || substr(md5(text), 1, 8))::BIGINT AS code, concat_ws('-', lang, source) AS tag, levenshtein(lang, source)::INT AS far, string_split(source, 'c')[1] AS part FROM documents""")
def _(spark, sf):
    h = F.substring(F.md5(F.col("text").cast("binary")), 1, 8)
    return load(spark, sf, "documents").select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]{9,})"), 1)).alias("words"), h.alias("head"), F.conv(h, 16, 10).cast("bigint").alias("code"), F.concat_ws("-", "lang", "source").alias("tag"), F.levenshtein("lang", "source").alias("far"), F.split("source", "c")[0].alias("part"))


@query("math_functions", "SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity) + ln(1 + l_quantity) + exp(-l_quantity / 10) + pow(l_quantity, 0.5), 6)::DOUBLE AS x, ((l_partkey - l_suppkey) % 7 + 7) % 7 AS r, sign(l_quantity - 25)::INT AS s, greatest(l_partkey, l_suppkey) AS g FROM lineitem")
def _(spark, sf):
    q = F.col("l_quantity")
    return load(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.sqrt(q) + F.ln(1 + q) + F.exp(-q / 10) + F.pow(q, F.lit(0.5)), 6).alias("x"), F.pmod(F.col("l_partkey") - F.col("l_suppkey"), F.lit(7)).alias("r"), F.signum(q - 25).cast("int").alias("s"), F.greatest("l_partkey", "l_suppkey").alias("g"))


@query("array_functions", """SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4)::DOUBLE AS norm, len(list_filter(embedding, lambda x: x > 0))::INT AS positive, list_sort(embedding)[1]::DOUBLE AS low, label IN (1, 2) AS some FROM embeddings""")
def _(spark, sf):
    e = F.transform("embedding", lambda x: x.cast("double"))
    square = F.aggregate(F.zip_with(e, e, lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    return load(spark, sf, "embeddings").select("vec_id", F.round(square, 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.array_sort("embedding")[0].cast("double").alias("low"), F.arrays_overlap(F.array("label"), F.array(F.lit(1), F.lit(2))).alias("some"))


@query("map_functions", with_graph("SELECT node, list_sort(list(k)) AS strengths, max(CASE WHEN slice = 3 THEN k END) AS third FROM k GROUP BY node", SMALL))
def _(spark, sf):
    k = strengths(graph(spark, sf, SMALL).edges)
    m = F.map_from_entries(F.collect_list(F.struct("slice", "k_out")))
    rows = k.groupBy("node").agg(m.alias("m"))
    return rows.select("node", F.array_sort(F.map_values(F.map_concat("m"))).alias("strengths"), F.try_element_at("m", F.lit(3)).alias("third"))


@query("json_functions", "SELECT event_id, (props::JSON->>'k')::INT AS k, '{\"user\":' || user_id || '}' AS packed FROM events")
def _(spark, sf):
    return load(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.to_json(F.struct(F.col("user_id").alias("user"))).alias("packed"))


@query("from_frames", with_graph("SELECT slice, src, dst, weight FROM e WHERE slice IN (0, 1, 2)"))
def _(spark, sf):
    e = graph(spark, sf).edges
    return files.from_frames([(t, snapshot(e, t).drop("slice")) for t in range(3)])


@query("edge_triplets", with_graph(f", {SUPRA_SQL} SELECT a + 1 AS row, b + 1 AS col, weight::DOUBLE AS value FROM s", SMALL))
def _(spark, sf):
    return files.to_triplets(supra_graph(graph(spark, sf, SMALL)).edges)


@query("edges_roundtrip", with_graph("SELECT f AS form, slice, count(*) AS n, sum(weight) AS w FROM e, (SELECT unnest(['csv', 'json', 'orc', 'parquet', 'slices']) AS f) GROUP BY ALL", SMALL))
def _(spark, sf):
    import uuid

    from .session import scratch_dir

    e = cut(graph(spark, sf, SMALL).edges, "edges")
    base, out = f"{scratch_dir(spark)}/roundtrip-{uuid.uuid4().hex}", []
    for form in ("csv", "json", "orc", "parquet"):
        files.write_edges(e, f"{base}/{form}", form)
        out.append(files.read_edges(spark, f"{base}/{form}", form).withColumn("form", F.lit(form)))
    files.write_edges(e, f"{base}/slices", by_slice=True)
    out.append(files.read_snapshots(spark, f"{base}/slices").withColumn("form", F.lit("slices")))
    return reduce(DataFrame.unionByName, out).groupBy("form", "slice").agg(F.count("*").alias("n"), F.sum("weight").alias("w"))


# ---------------------------------------------------------------- streams; only windows closed at the end of the table


def _stream(spark, sf):
    return streaming.events_stream(spark, f"{sf}/events.parquet")


_CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"


@query("stream_tumbling", f"SELECT * FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS start, user_id, event_type, count(*)::DOUBLE AS weight FROM events GROUP BY ALL) WHERE start + INTERVAL 1 DAY <= {_CLOSED}")
def _(spark, sf):
    return run_to_table(streaming.tumbling_edges(_stream(spark, sf))).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sliding", f"SELECT * FROM (SELECT (date_trunc('day', ts) - s * INTERVAL 1 DAY)::TIMESTAMP AS start, user_id, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS s) GROUP BY ALL) WHERE start + INTERVAL 2 DAY <= {_CLOSED}")
def _(spark, sf):
    rows = run_to_table(streaming.sliding_counts(_stream(spark, sf)))
    return rows.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sessions", f"""WITH g AS (SELECT *, sum(CASE WHEN prev IS NULL OR ts > prev + INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS run FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS prev FROM events))
  SELECT min(ts)::TIMESTAMP AS start, (max(ts) + INTERVAL 6 HOUR)::TIMESTAMP AS stop, user_id, count(*) AS n FROM g GROUP BY user_id, run HAVING max(ts) + INTERVAL 6 HOUR <= {_CLOSED}""")
def _(spark, sf):
    rows = run_to_table(streaming.session_contacts(_stream(spark, sf)))
    return rows.withColumns({"start": F.col("start").cast("timestamp_ntz"), "stop": F.col("stop").cast("timestamp_ntz")})


@query("stream_dedup", "SELECT event_id, user_id, event_type FROM events")
def _(spark, sf):
    twice = _stream(spark, sf)
    return run_to_table(streaming.dedup(twice.union(_stream(spark, sf))).select("event_id", "user_id", "event_type"))


@query("stream_contacts", "SELECT a.user_id AS src, b.user_id AS dst, count(*) AS n FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 10 MINUTE GROUP BY ALL")
def _(spark, sf):
    return run_to_table(streaming.stream_contacts(_stream(spark, sf), _stream(spark, sf))).groupBy("src", "dst").agg(F.count("*").alias("n"))


@query("stream_degrees", "SELECT user_id AS node, count(DISTINCT date_trunc('hour', ts)) AS seen FROM events GROUP BY user_id")
def _(spark, sf):
    return run_to_table(streaming.running_degrees(_stream(spark, sf))).groupBy("node").agg(F.max("seen").alias("seen"))


@query("stream_communities", "SELECT datediff('day', DATE '1970-01-01', ts::DATE)::INT AS slice, count(DISTINCT user_id) AS users FROM events WHERE ts::DATE + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY 1")
def _(spark, sf):
    """The users labelled in each closed window."""
    rows = streaming.warm_communities(_stream(spark, sf), lambda tg, start: plans.leiden(tg, 1.0, backend_name="kernel", start=start))
    return rows.filter(F.col("node") < (1 << 36)).groupBy("slice").agg(F.countDistinct("node").alias("users"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts bought together, quarter by quarter: communities of the per-slice objective and their timeline."""
    tg = graph(spark, sf_dir, "copart_quarter")
    return tracking.community_timeline(tg.edges, plans.leiden(tg))
