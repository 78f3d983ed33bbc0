"""The engine's registered queries on the given tables, and their SQL twins."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import functions as fn
from .operators import ballots as bl
from .operators import checks, components, metrics, paths, rankedpairs, reductions, rule, scores, synth
from .operators import margins as mg
from .operators.graph import PrefGraph, from_edges
from .plans import alike
from .plans import winners as wn
from .plans.storage import number, shared_folder, store
from .sources import load, read_ballots, read_graph, write_graph, write_log

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


# ---- workloads: (ballots, SQL of a CTE b(voter, alt, rank, weight)) ---------------------------


def _chart_sql(k: int | None, region: str | None = None, alt: str = "l_suppkey", period: str = "month", value: str = "CAST(l_quantity AS BIGINT)", weight: str = "1") -> str:
    dims = "JOIN part ON p_partkey = l_partkey" if alt.startswith("p_") else "JOIN supplier ON s_suppkey = l_suppkey" if alt == "s_nationkey" else ""
    place = f"JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey AND r_name = '{region}'" if region else ""
    return f"""sc AS (SELECT CAST(year(o_orderdate) * 100 + {period}(o_orderdate) AS VARCHAR) || '-' || CAST(c_nationkey AS VARCHAR) AS voter, c_nationkey AS nat, {alt} AS alt, sum({value}) AS score
  FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey {place} {dims} GROUP BY 1, 2, 3),
b AS (SELECT voter, alt, rank, {weight} AS weight FROM (SELECT voter, nat, alt, rank() OVER (PARTITION BY voter ORDER BY score DESC) AS rank FROM sc){f' WHERE rank <= {k}' if k else ''})"""


_WEIGHT = "(SELECT count(*) FROM customer WHERE c_nationkey = nat)"
WORKLOADS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "w1s": (lambda s, d: bl.chart_ballots(s, d, region="EUROPE", k=15), _chart_sql(15, "EUROPE")),
    "w2s": (lambda s, d: bl.chart_ballots(s, d, region="EUROPE", k=20), _chart_sql(20, "EUROPE")),
    "w3s": (lambda s, d: bl.chart_ballots(s, d, k=15), _chart_sql(15)),
    "w4s": (lambda s, d: bl.chart_ballots(s, d, k=20), _chart_sql(20)),
    "w1": (lambda s, d: bl.chart_ballots(s, d, region="EUROPE", k=15, alt="l_partkey"), _chart_sql(15, "EUROPE", "l_partkey")),
    "w2": (lambda s, d: bl.chart_ballots(s, d, region="EUROPE", k=20, alt="l_partkey"), _chart_sql(20, "EUROPE", "l_partkey")),
    "w3": (lambda s, d: bl.chart_ballots(s, d, k=15, alt="l_partkey"), _chart_sql(15, alt="l_partkey")),
    "w4": (lambda s, d: bl.chart_ballots(s, d, k=20, alt="l_partkey"), _chart_sql(20, alt="l_partkey")),
    "w11": (lambda s, d: bl.chart_ballots(s, d, period="quarter", region="EUROPE", k=None), _chart_sql(None, "EUROPE", period="quarter")),
    "w12b": (lambda s, d: bl.chart_ballots(s, d, k=10, alt="p_brand"), _chart_sql(10, alt="p_brand")),
    "w12c": (lambda s, d: bl.chart_ballots(s, d, k=10, alt="p_name"), _chart_sql(10, alt="p_name")),
}


def _nation_ballots(s: SparkSession, d: str) -> DataFrame:
    month = (F.year("l_shipdate") * 100 + F.month("l_shipdate")).cast("string")
    rows = load(s, d, "lineitem").select("l_suppkey", month.alias("voter"), F.col("l_extendedprice").cast("decimal(18,2)").alias("x")).join(load(s, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return bl.from_scores(rows.groupBy("voter", F.col("s_nationkey").cast("long").alias("alt")).agg(F.sum("x").alias("score")), "voter", "alt", "score")


def _event_ballots(s: SparkSession, d: str) -> DataFrame:
    return bl.from_scores(load(s, d, "events").groupBy("user_id", "event_type").count(), "user_id", "event_type", "count")


def _weighted(s: SparkSession, d: str) -> DataFrame:
    weights = load(s, d, "customer").groupBy("c_nationkey").count().select(F.col("c_nationkey").cast("string").alias("nat"), F.col("count").alias("weight"))
    b = bl.chart_ballots(s, d, k=20)
    of = b.select("voter").distinct().withColumn("nat", F.substring_index("voter", "-", -1)).join(weights, "nat").select("voter", "weight")
    return bl.with_weights(b, of)


def _real_weighted(s: SparkSession, d: str) -> DataFrame:
    """Voters weigh their nation's balances, in cents."""
    weights = load(s, d, "customer").groupBy("c_nationkey").agg(F.sum(F.abs(F.col("c_acctbal").cast("decimal(12,2)"))).cast("decimal(14,2)").alias("weight"))
    b = bl.chart_ballots(s, d, k=20)
    of = b.select("voter").distinct().withColumn("nat", F.substring_index("voter", "-", -1).cast("int")).join(weights, F.col("nat") == F.col("c_nationkey")).select("voter", "weight")
    return bl.with_weights(b, of)


_REAL_WEIGHT = "(SELECT sum(abs(CAST(c_acctbal AS DECIMAL(12, 2)))) FROM customer WHERE c_nationkey = nat)"
_RANKED = "b AS (SELECT voter, alt, rank() OVER (PARTITION BY voter ORDER BY score DESC) AS rank, 1 AS weight FROM sc)"
WORKLOADS |= {
    "w5": (_weighted, _chart_sql(20, weight=_WEIGHT)),
    "w5r": (_real_weighted, _chart_sql(20, weight=_REAL_WEIGHT)),
    "w10": (
        lambda s, d: bl.from_vectors(load(s, d, "embeddings"), "vec_id", "embedding"),
        f"sc AS (SELECT i AS voter, vec_id AS alt, embedding[i] AS score FROM embeddings, range(1, 65) AS r(i)), {_RANKED}",
    ),
    "w12a": (
        _nation_ballots,
        f"sc AS (SELECT year(l_shipdate) * 100 + month(l_shipdate) AS voter, CAST(s_nationkey AS BIGINT) AS alt, sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS score FROM lineitem JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2), {_RANKED}",
    ),
    "w12d": (_event_ballots, f"sc AS (SELECT user_id AS voter, event_type AS alt, count(*) AS score FROM events GROUP BY 1, 2), {_RANKED}"),
    "docs": (
        lambda s, d: bl.from_scores(load(s, d, "documents").groupBy("lang", "source").agg(F.sum("n_chars").alias("n")), "lang", "source", "n"),
        f"sc AS (SELECT lang AS voter, source AS alt, sum(n_chars) AS score FROM documents GROUP BY 1, 2), {_RANKED}",
    ),
}

_CO = "c AS (SELECT x.alt AS a, y.alt AS b, sum(x.weight * sign(y.rank - x.rank)) AS c FROM b x JOIN b y ON x.voter = y.voter AND x.alt <> y.alt GROUP BY 1, 2)"
_MARGINS = f"""n AS (SELECT alt, sum(weight) AS n FROM b GROUP BY 1), {_CO},
m AS (SELECT p.alt AS a, q.alt AS b, CAST(coalesce(c, 0) + p.n - q.n AS BIGINT) AS margin FROM n p JOIN n q ON p.alt <> q.alt LEFT JOIN c ON c.a = p.alt AND c.b = q.alt),
e AS (SELECT a, b, margin AS w FROM m WHERE margin > 0)"""


def _closure(steps: int = 8, source: str = "e", p: str = "p", beat: str = "beat") -> str:
    out = [f"{p}0 AS MATERIALIZED (SELECT a, b, w FROM {source})"]
    for i in range(steps):
        out.append(f"{p}{i + 1} AS MATERIALIZED (SELECT a, b, max(w) AS w FROM (SELECT * FROM {p}{i} UNION ALL SELECT x.a, y.b, least(x.w, y.w) FROM {p}{i} x JOIN {p}{i} y ON x.b = y.a AND x.a <> y.b) GROUP BY 1, 2)")
    return ", ".join([*out, f"{p} AS (SELECT a, b, w FROM {p}{steps})", f"{beat} AS (SELECT x.a, x.b FROM {p} x LEFT JOIN {p} y ON x.a = y.b AND x.b = y.a WHERE x.w > coalesce(y.w, 0))"])


def _searches(name: str, sources: str, steps: int) -> str:
    """CTEs {name}o and {name}i: widths from each of sources(s) to a vertex v and back, along up to steps edges."""
    out = []
    for d, near, far in (("o", "a", "b"), ("i", "b", "a")):
        out.append(f"{name}{d}0 AS MATERIALIZED (SELECT s, s AS v, CAST(9000000000000000 AS DECIMAL(18, 0)) AS w FROM ({sources}))")
        for k in range(steps):
            out.append(f"{name}{d}{k + 1} AS MATERIALIZED (SELECT s, v, max(w) AS w FROM (SELECT * FROM {name}{d}{k} UNION ALL SELECT x.s, e.{far}, least(x.w, e.w) FROM {name}{d}{k} x JOIN e ON e.{near} = x.v) GROUP BY 1, 2)")
        out.append(f"{name}{d} AS (SELECT s, v, w FROM {name}{d}{steps})")
    return ", ".join(out)


def _winners_sql(head: str, steps: int) -> str:
    """Winners without all pairs: what one vertex does not beat is compared with all others."""
    first = "SELECT alt AS s FROM n LEFT JOIN (SELECT x, sum(w) AS t FROM (SELECT a AS x, w FROM e UNION ALL SELECT b, -w FROM e) GROUP BY 1) ON x = alt ORDER BY coalesce(t, 0) DESC, alt LIMIT 1"
    open_ = "SELECT alt AS s FROM n LEFT JOIN fo ON fo.v = alt LEFT JOIN fi ON fi.v = alt WHERE coalesce(fi.w, 0) >= coalesce(fo.w, 0)"
    return f"WITH {head}, e1 AS MATERIALIZED (SELECT a, b, w FROM e0), e AS (SELECT * FROM e1), {_searches('f', first, steps)}, open AS MATERIALIZED ({open_}), {_searches('g', 'SELECT s FROM open', steps)} SELECT s AS alt FROM open WHERE NOT EXISTS (SELECT 1 FROM gi LEFT JOIN go ON go.s = gi.s AND go.v = gi.v WHERE gi.s = open.s AND gi.v <> gi.s AND gi.w > coalesce(go.w, 0))"


def _sql(workload: str, tail: str, closure: bool = False) -> str:
    steps = 11 if workload == "w10" else 8  # paths of up to 2^steps edges
    margins = _MARGINS.replace("AS BIGINT) AS margin", "AS DECIMAL(24, 2)) AS margin") if workload == "w5r" else _MARGINS
    return f"WITH {WORKLOADS[workload][1]}, {margins}{', ' + _closure(steps) if closure else ''} {tail}"


_WON = "SELECT alt FROM n WHERE alt NOT IN (SELECT b FROM beat)"


def ballots_of(workload: str) -> Query:
    return WORKLOADS[workload][0]


def graph(s: SparkSession, d: str, workload: str) -> PrefGraph:
    return mg.graph_of(store(ballots_of(workload)(s, d), "ballots"))


def _named(g: PrefGraph, found: DataFrame) -> DataFrame:
    return g.vertices.join(found, "id", "left_semi").select("alt")


# ---- ballots ------------------------------------------------------------------------------

for _w, _label in (("w4s", "ballots_global20_supplier"), ("w2s", "ballots_europe20_supplier"), ("w12d", "ballots_events"), ("w10", "ballots_embeddings"), ("docs", "ballots_documents")):
    _voter = "voter - 1" if _w == "w10" else "voter"  # SQL counts list places from 1
    query(f"WITH {WORKLOADS[_w][1]} SELECT CAST({_voter} AS VARCHAR) AS voter, alt, CAST(rank AS INT) AS rank, CAST(weight AS BIGINT) AS weight FROM b", _label)(ballots_of(_w))


@query("SELECT l_orderkey AS voter, l_suppkey AS alt, 'listed twice' AS problem FROM lineitem GROUP BY 1, 2 HAVING count(*) > 1 UNION ALL SELECT l_orderkey, l_suppkey, 'missing value' FROM lineitem WHERE l_returnflag = 'R'")
def ballot_validation(s, d):
    """Order lines as if they were ballots, without a rank where the line was returned: suppliers that an order names twice, and what is missing."""
    rows = load(s, d, "lineitem").select(F.col("l_orderkey").alias("voter"), F.col("l_suppkey").alias("alt"), F.when(F.col("l_returnflag") != "R", F.col("l_linenumber")).alias("rank"))
    return bl.validate(rows)


@query("WITH " + WORKLOADS["w12d"][1] + " SELECT CAST(voter AS VARCHAR) AS voter, alt, CAST(rank AS INT) AS rank, CAST(1 AS BIGINT) AS weight FROM b")
def ballots_nested_round_trip(s, d):
    return bl.unnest(bl.nest(_event_ballots(s, d))).select("voter", "alt", "rank", "weight")


@query("WITH " + WORKLOADS["w3s"][1] + " SELECT voter, alt, CAST(rank AS INT) AS rank, CAST(weight AS BIGINT) AS weight FROM b")
def ballots_truncated(s, d):
    return bl.truncate(ballots_of("w4s")(s, d), 15)


@query("WITH l AS (SELECT user_id, max(ts) AS ts FROM events WHERE ts <= TIMESTAMP '2024-01-16' GROUP BY 1) SELECT CAST(user_id AS VARCHAR) AS voter, event_type AS alt FROM events JOIN l USING (user_id, ts)")
def ballots_as_of(s, d):
    rows = load(s, d, "events").select(F.col("user_id").cast("string").alias("voter"), F.col("event_type").alias("alt"), "ts")
    return bl.as_of(rows, "ts", F.lit("2024-01-16").cast("timestamp")).select("voter", "alt")


@query(
    "WITH o AS (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events), "
    "g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM o), "
    "t AS (SELECT user_id, g, event_type, count(*) AS n FROM g GROUP BY 1, 2, 3), r AS (SELECT rank() OVER (PARTITION BY user_id, g ORDER BY n DESC) AS rank, event_type FROM t) "
    "SELECT event_type AS alt, CAST(rank AS INT) AS rank, count(*) AS n FROM r GROUP BY 1, 2"
)
def ballots_by_session(s, d):
    return bl.by_session(load(s, d, "events"), "12 hours").groupBy("alt", "rank").agg(F.count(F.lit(1)).alias("n"))


@query("WITH " + WORKLOADS["w12d"][1] + " SELECT alt, CAST(rank AS INT) AS rank, count(*) AS n FROM b GROUP BY 1, 2")
def ballots_written_and_read(s, d):
    path = f"{shared_folder(s)}/ballots-{uuid.uuid4().hex}"
    _event_ballots(s, d).write.option("header", "true").csv(path)
    return read_ballots(s, path, "csv").groupBy("alt", "rank").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def page_hosts(s, d):
    return load(s, d, "pages").groupBy(fn.url_host(F.col("url")).alias("host")).agg(F.count(F.lit(1)).alias("n"))


# ---- margins and graphs -------------------------------------------------------------------


@query(
    "WITH " + WORKLOADS["w12a"][1] + ", n AS (SELECT DISTINCT alt FROM b), v AS (SELECT DISTINCT voter FROM b), f AS (SELECT voter, n.alt, coalesce(rank, 1000000) AS rank FROM v CROSS JOIN n LEFT JOIN b USING (voter, alt)) "
    "SELECT x.alt AS a, y.alt AS b, count(*) AS prefer FROM f x JOIN f y ON x.voter = y.voter AND x.rank < y.rank GROUP BY 1, 2"
)
def pairwise_counts(s, d):
    return mg.pairwise_counts(_nation_ballots(s, d))


query(_sql("w4s", "SELECT a, b, margin FROM m"), "majority_margins")(lambda s, d: mg.majority_margins(ballots_of("w4s")(s, d)))
query(_sql("w5", "SELECT a, b, margin FROM m"), "majority_margins_weighted")(lambda s, d: mg.majority_margins(_weighted(s, d)))
query(_sql("w12a", "SELECT a, b FROM e"), "dominance_edges")(lambda s, d: mg.dominance(mg.majority_margins(_nation_ballots(s, d))))
query(f"WITH {WORKLOADS['w12d'][1]}, {_CO} SELECT a, b, CAST(c AS BIGINT) AS margin FROM c", "margins_head_to_head")(lambda s, d: mg.head_to_head(_event_ballots(s, d)))


@query(f"WITH {WORKLOADS['w12d'][1]}, {_CO} SELECT a, b, CAST(2 * c AS BIGINT) AS margin FROM c")
def margins_added(s, d):
    m = mg.head_to_head(_event_ballots(s, d))
    return mg.add(m, m)


@query(
    "WITH " + _chart_sql(20) + ", v AS (SELECT b.*, r_name FROM b JOIN nation ON n_nationkey = CAST(split_part(voter, '-', 2) AS INT) JOIN region ON r_regionkey = n_regionkey), "
    "k AS (SELECT r_name, grouping(r_name) AS g, alt, sum(weight) AS n FROM v GROUP BY GROUPING SETS ((r_name, alt), (alt))), "
    "c AS (SELECT r_name, grouping(r_name) AS g, x.alt AS a, y.alt AS b, sum(x.weight * sign(y.rank - x.rank)) AS c FROM v x JOIN v y USING (voter, r_name) WHERE x.alt < y.alt GROUP BY GROUPING SETS ((r_name, x.alt, y.alt), (x.alt, y.alt))) "
    "SELECT p.r_name, p.alt AS a, q.alt AS b, CAST(coalesce(c, 0) + p.n - q.n AS BIGINT) AS margin FROM k p JOIN k q ON p.g = q.g AND p.r_name IS NOT DISTINCT FROM q.r_name AND p.alt < q.alt "
    "LEFT JOIN c ON c.g = p.g AND c.r_name IS NOT DISTINCT FROM p.r_name AND c.a = p.alt AND c.b = q.alt"
)
def margins_by_region_rollup(s, d):
    place = load(s, d, "nation").join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").cast("string").alias("nat"), "r_name")
    b = ballots_of("w4s")(s, d).withColumn("nat", F.substring_index("voter", "-", -1)).join(F.broadcast(place), "nat")
    return alike.margins_by_group(store(b, "ballots"), "r_name").select("r_name", "a", "b", "margin")


for _w in ("w1s", "w2s", "w3s", "w4s", "w1", "w2", "w3", "w4"):
    query(_sql(_w, "SELECT a AS src, b AS dst, w FROM e"), f"wmg_edges_{_w}")(lambda s, d, w=_w: (lambda g: g.named(g.edges, "src", "dst"))(graph(s, d, w)))
    query(
        _sql(_w, "SELECT (SELECT count(*) FROM n) AS alternatives, count(*) AS edges, max(w) AS max_weight, round(count(*) / ((SELECT count(*) FROM n) * ((SELECT count(*) FROM n) - 1) / 2), 6) AS density FROM e"), f"wmg_stats_{_w}",
    )(lambda s, d, w=_w: metrics.graph_stats(graph(s, d, w)))
    query(
        _sql(_w, "SELECT count(*) AS undecided FROM n LEFT JOIN (SELECT b, max(w) AS i FROM e GROUP BY 1) ON b = alt LEFT JOIN (SELECT a, max(w) AS o FROM e GROUP BY 1) ON a = alt WHERE coalesce(i, 0) <= coalesce(o, 0)"), f"undecided_after_init_{_w}",
    )(lambda s, d, w=_w: wn.initial_status(graph(s, d, w)).filter(F.col("status") == wn.UNKNOWN).agg(F.count(F.lit(1)).alias("undecided")))

_BORDA = "SELECT alt, CAST(coalesce((SELECT sum(margin) FROM m WHERE a = alt), 0) AS BIGINT) AS borda FROM n"
query(_sql("w4s", f"SELECT alt, borda, row_number() OVER (ORDER BY borda DESC, alt) AS id FROM ({_BORDA})"), "borda_ids")(lambda s, d: graph(s, d, "w4s").vertices.select("alt", "borda", "id"))
query(_sql("w12a", "SELECT a AS alt FROM e GROUP BY 1 HAVING count(*) = (SELECT count(*) - 1 FROM n)"), "condorcet_winner")(lambda s, d: (lambda g: _named(g, scores.condorcet_winner(g)))(graph(s, d, "w12a")))
query(_sql("w4s", "SELECT alt, (SELECT count(*) FROM e WHERE a = alt) AS wins FROM n ORDER BY 2 DESC, 1 LIMIT 10"), "most_wins")(lambda s, d: (lambda g: scores.wins(g).join(g.vertices, "id").select("alt", "wins").orderBy(F.desc("wins"), "alt").limit(10))(graph(s, d, "w4s")))
query(_sql("w4s", f"SELECT alt, CAST(ntile(4) OVER (ORDER BY borda DESC, alt) AS INT) AS quartile FROM ({_BORDA})"), "borda_quartiles")(lambda s, d: scores.quartile(graph(s, d, "w4s").vertices))
query(_sql("w4s", "SELECT w, count(*) AS n FROM e GROUP BY 1"), "weight_histogram")(lambda s, d: metrics.weight_histogram(graph(s, d, "w4s")))


@query(_sql("w4s", "SELECT alt, (SELECT count(*) FROM e WHERE a = alt) AS out_degree, (SELECT count(*) FROM e WHERE b = alt) AS in_degree, coalesce((SELECT max(w) FROM e WHERE a = alt), 0) AS max_out, coalesce((SELECT max(w) FROM e WHERE b = alt), 0) AS max_in FROM n"))
def vertex_stats(s, d):
    g = graph(s, d, "w4s")
    return metrics.vertex_stats(g).join(g.vertices, "id").select("alt", "out_degree", "in_degree", "max_out", "max_in")


@query(_sql("w12a", "SELECT a AS src, b AS dst, w FROM e"))
def graph_written_and_read(s, d):
    path = f"{shared_folder(s)}/graph-{uuid.uuid4().hex}"
    write_graph(graph(s, d, "w12a"), path)
    g = read_graph(s, path)
    return g.named(g.edges, "src", "dst")


@query(_sql("w4s", f"SELECT alt, CAST(sum(borda) OVER (ORDER BY borda DESC, alt ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM ({_BORDA})"))
def borda_running_sum(s, d):
    order = Window.orderBy("id").rowsBetween(Window.unboundedPreceding, 0)
    return graph(s, d, "w4s").vertices.select("alt", F.sum("borda").over(order).cast("long").alias("running"))


@query(f"WITH {WORKLOADS['w12a'][1]} SELECT alt, CAST(voter AS VARCHAR) AS month, CAST(rank - lag(rank) OVER (PARTITION BY alt ORDER BY voter) AS INT) AS moved FROM b")
def rank_change_by_month(s, d):
    moved = F.col("rank") - F.lag("rank").over(Window.partitionBy("alt").orderBy("voter"))
    return _nation_ballots(s, d).select("alt", F.col("voter").alias("month"), moved.cast("int").alias("moved"))


# ---- paths and the rule --------------------------------------------------------------------

_EXAMPLE = [(1, 2, 4), (1, 3, 6), (2, 3, 10), (3, 4, 8), (4, 1, 2), (4, 2, 12)]
_EXAMPLE_SQL = "WITH e(a, b, w) AS (VALUES " + ", ".join(f"(CAST({a} AS BIGINT), CAST({b} AS BIGINT), CAST({w} AS BIGINT))" for a, b, w in _EXAMPLE) + "), " + _closure(3)
query(_EXAMPLE_SQL + " SELECT a, b, w AS width FROM p", "widest_paths_example")(lambda s, d: paths.all_pairs_widest(from_edges(s, _EXAMPLE), "squaring"))
for _m in ("fw", "squaring", "blocked", "vertex"):
    query(_sql("w12a", "SELECT a, b, w AS width FROM p", True), f"widest_paths_{_m}")(lambda s, d, m=_m: (lambda g: g.named(paths.all_pairs_widest(g, m), "a", "b"))(graph(s, d, "w12a")))


def _top(g: PrefGraph) -> DataFrame:
    return g.vertices.filter("id = 1").select("id")


_FIRST = f"(SELECT alt FROM ({_BORDA}) ORDER BY borda DESC, alt LIMIT 1)"
query(_sql("w4s", f"SELECT b AS alt, w AS width FROM p WHERE a = {_FIRST}", True), "widest_from_source")(lambda s, d: (lambda g: paths.widest_from(g, _top(g)).join(g.vertices, "id").select("alt", "width"))(graph(s, d, "w4s")))
query(_sql("w4s", f"SELECT a AS alt, w AS width FROM p WHERE b = {_FIRST}", True), "widest_to_target")(lambda s, d: (lambda g: paths.widest_from(g, _top(g), "in").join(g.vertices, "id").select("alt", "width"))(graph(s, d, "w4s")))


def _exists(strict: bool) -> Query:
    """Whether a path from the first alternative by Borda score to the last is as wide as the least weight, as the greatest, and as the widest such path is."""

    def run(s: SparkSession, d: str) -> DataFrame:
        g = graph(s, d, "w12a")
        last = g.vertices.agg(F.max("id")).first()[0]
        low, high = g.edges.agg(F.min("w"), F.max("w")).first()
        width = paths.widest_from(g, _top(g)).filter(F.col("id") == last).first()
        asked = sorted({w for w in (low, high, width and width.width) if w is not None})
        return s.createDataFrame([(w, paths.wide_path_exists(g, 1, last, w, strict)) for w in asked], "w long, found boolean")

    return run


_LAST = f"(SELECT alt FROM ({_BORDA}) ORDER BY borda, alt DESC LIMIT 1)"
for _n, _o in (("wide_path_ge", ">="), ("wide_path_gt", ">")):
    query(_sql("w12a", f", z AS MATERIALIZED (SELECT w FROM p WHERE a = {_FIRST} AND b = {_LAST}), x AS (SELECT min(w) AS t FROM e UNION SELECT max(w) FROM e UNION SELECT w FROM z) SELECT t AS w, EXISTS (SELECT 1 FROM z WHERE z.w {_o} t) AS found FROM x WHERE t IS NOT NULL", True).replace(") , z", "), z"), _n)(_exists(_o == ">"))


@query(_EXAMPLE_SQL + " SELECT a, b, w AS width FROM p WHERE (a, b) IN ((1, 4), (2, 1), (4, 3))")
def widest_by_threshold(s, d):
    g = from_edges(s, _EXAMPLE)
    return s.createDataFrame([(a, b, paths.widest_by_threshold(g, a, b)) for a, b in ((1, 4), (2, 1), (4, 3))], "a long, b long, width long")


query(_sql("w12a", "SELECT a, b FROM beat", True), "beats")(lambda s, d: (lambda g: g.named(rule.beats(paths.all_pairs_widest(g, "fw")), "a", "b"))(graph(s, d, "w12a")))
query(_sql("w12a", "SELECT x.alt AS a, y.alt AS b FROM n x JOIN n y ON x.alt <> y.alt WHERE NOT EXISTS (SELECT 1 FROM beat WHERE beat.a = y.alt AND beat.b = x.alt)", True), "relation_at_least_as_good")(
    lambda s, d: (lambda g: g.named(rule.relation(paths.all_pairs_widest(g, "fw"), g.vertices), "a", "b"))(graph(s, d, "w12a"))
)
_RANKING = "SELECT alt, beaten_by, beats, rank() OVER (ORDER BY beaten_by) AS rnk FROM (SELECT alt, (SELECT count(*) FROM beat WHERE b = alt) AS beaten_by, (SELECT count(*) FROM beat WHERE a = alt) AS beats FROM n)"
query(_sql("w4s", _RANKING, True), "ranking_supplier")(lambda s, d: alike.ranking(store(ballots_of("w4s")(s, d), "ballots")))

for _w, _label in (("w1s", "winners_w1s"), ("w2s", "winners_w2s"), ("w3s", "winners_w3s"), ("w4s", "winners_w4s"), ("w5", "winners_weighted"), ("w10", "winners_embeddings"), ("w11", "winners_quarter"), ("w12b", "winners_brand"), ("w12c", "winners_name"), ("w12d", "winners_events"), ("docs", "winners_documents")):
    query(_sql(_w, _WON, True), _label)(lambda s, d, w=_w: alike.winners(store(ballots_of(w)(s, d), "ballots")))
for _w in ("w1", "w2", "w3", "w4"):
    query(_winners_sql(f"{WORKLOADS[_w][1]}, {_MARGINS.replace('e AS (', 'e0 AS (')}", 8), f"winners_{_w}")(lambda s, d, w=_w: (lambda g: _named(g, wn.find_winners(g).winners))(graph(s, d, w)))
_LITERAL = {"strategy": "labels", "finish_threshold": 0}
for _label, _flags in {
    "labels": {**_LITERAL, "prune": "zero"}, "pivot": {"strategy": "pivot"}, "no_init": {"init": False}, "no_combiner": {**_LITERAL, "combiner": False}, "prune_none": {**_LITERAL, "prune": "none", "init": False},
    "prune_drop": {**_LITERAL, "init": False}, "ids_key": {**_LITERAL, "ids": "key"}, "ids_random": {**_LITERAL, "ids": "random"}, "ids_ascending": {**_LITERAL, "ids": "borda_asc"}, "three_labels": {**_LITERAL, "labels": 3, "ids": "borda_asc"},
}.items():
    query(_sql("w12a", _WON, True), f"winners_flags_{_label}")(lambda s, d, f=_flags: (lambda g: _named(g, wn.find_winners(g, **f).winners))(graph(s, d, "w12a")))
for _label, _flags in {"labels": _LITERAL, "pivot": {"strategy": "pivot"}, "auto": {}}.items():
    query(_sql("w5r", _WON, True), f"winners_real_weights_{_label}")(lambda s, d, f=_flags: (lambda g: _named(g, wn.find_winners(g, **f).winners))(graph(s, d, "w5r")))
query(_sql("w5", _WON, True), "winners_weights_beyond_31_bits")(lambda s, d: (lambda g: _named(g, wn.find_winners(PrefGraph(g.vertices, g.edges.withColumn("w", F.col("w") * F.lit(1 << 33))), **_LITERAL).winners))(graph(s, d, "w5")))
query(_sql("w5r", "SELECT a, b, CAST(w AS DOUBLE) AS width FROM p", True), "widest_paths_real_weights")(lambda s, d: alike.widest_paths(store(_real_weighted(s, d), "ballots")).select("a", "b", F.col("width").cast("double").alias("width")))


@query()
def ablations(s, d):
    """Rounds, supersteps and rows that moved of the label method, as it is and with each of its parts changed, on the graph of classes of suppliers
    that all voters rank alike; winners are suppliers."""
    b, rows = alike.Alike(store(ballots_of("w4s")(s, d), "ballots")), []
    g = b.graph()
    for name, flags in {"as it is": {}, "ids by key": {"ids": "key"}, "ids ascending": {"ids": "borda_asc"}, "no pruning": {"prune": "none"}, "no initial status": {"init": False}, "four labels": {"labels": 4}}.items():
        found = wn.find_winners(g, **_LITERAL, **flags)
        steps = [x for r in found.log for x in r.get("steps", [])]
        rows.append((name, found.rounds, found.supersteps, sum(x["active"] for x in steps), max([0, *(x["state_bytes"] for x in steps)]), b.all_of(_named(g, found.winners)).count()))
    return s.createDataFrame(rows, "variant string, rounds int, supersteps int, active long, state_bytes long, winners long")


def _head_to_head(s: SparkSession, d: str, alt: str) -> PrefGraph:
    """Alternatives of one order, compared by the quantity in it; pairs of no common order stay without an edge."""
    rows = load(s, d, "lineitem").groupBy(F.col("l_orderkey").alias("voter"), F.col(alt).alias("alt")).agg(F.sum(F.col("l_quantity").cast("long")).alias("score"))
    return mg.graph_of(store(bl.from_scores(rows, "voter", "alt", "score"), "ballots"), unlisted="ignore")


def _head_to_head_sql(alt: str, edges: str) -> str:
    return f"sc AS (SELECT l_orderkey AS voter, {alt} AS alt, sum(CAST(l_quantity AS BIGINT)) AS score FROM lineitem GROUP BY 1, 2), {_RANKED}, n AS (SELECT DISTINCT alt FROM b), {_CO}, {edges} AS (SELECT a, b, CAST(c AS BIGINT) AS w FROM c WHERE c > 0)"


query(f"WITH {_head_to_head_sql('l_suppkey', 'e')}, {_closure()} {_WON}", "winners_headtohead_supplier")(lambda s, d: (lambda g: _named(g, wn.find_winners(g).winners))(_head_to_head(s, d, "l_suppkey")))
query(None, "winners_headtohead_part")(lambda s, d: (lambda g: _named(g, wn.find_winners(g).winners))(_head_to_head(s, d, "l_partkey")))

_IN_SCHWARTZ = "SELECT alt FROM n WHERE NOT EXISTS (SELECT 1 FROM p x WHERE x.b = alt AND NOT EXISTS (SELECT 1 FROM p y WHERE y.a = alt AND y.b = x.a))"
query(_sql("w12b", "SELECT alt, least(alt, coalesce((SELECT min(x.b) FROM p x JOIN p y ON x.a = y.b AND x.b = y.a WHERE x.a = alt), alt)) AS scc FROM n", True), "strong_components")(
    lambda s, d: (lambda g, c: c.withColumn("_x", F.min("alt").over(Window.partitionBy("scc"))).select("alt", F.col("_x").alias("scc")))(*(lambda g: (g, components.strongly_connected(g).join(g.vertices, "id")))(graph(s, d, "w12b")))
)
query(_sql("w11", _IN_SCHWARTZ, True), "schwartz_set")(lambda s, d: alike.schwartz_set(store(ballots_of("w11")(s, d), "ballots")))
_UNCOVERED = "SELECT alt FROM n WHERE alt NOT IN (SELECT x.b FROM e x LEFT JOIN e y ON y.a = x.b LEFT JOIN e z ON z.a = x.a AND z.b = y.b GROUP BY x.a, x.b HAVING count(y.b) = count(z.b))"
query(_sql("w11", _UNCOVERED), "uncovered_set")(lambda s, d: alike.uncovered_set(store(ballots_of("w11")(s, d), "ballots")))
query(_sql("w12c", _WON, True), "winners_via_schwartz")(lambda s, d: (lambda g: _named(g, wn.via_schwartz(g)))(graph(s, d, "w12c")))


@query(_sql("w12a", "SELECT a AS alt FROM beat WHERE b = " + _FIRST, True))
def beaters_of_the_borda_winner(s, d):
    g = graph(s, d, "w12a")
    return _named(g, rule.is_winner(g, 1)[1])


@query(_sql("w12d", f"SELECT alt, alt IN ({_WON}) AS winner, alt IN ({_WON}) AND (SELECT count(*) FROM ({_WON})) = 1 AS alone FROM n", True))
def verification(s, d):
    g = graph(s, d, "w12d")
    return s.createDataFrame([(r.alt, rule.is_winner(g, r.id)[0], rule.is_unique_winner(g, r.id)) for r in g.vertices.collect()], "alt string, winner boolean, alone boolean")


query(_sql("w12a", f"SELECT CAST(dense_rank() OVER (ORDER BY rnk) AS INT) AS tier, alt FROM ({_RANKING}) WHERE rnk <= 5", True), "topk_ranking")(lambda s, d: (lambda g: rule.top_k(g, 5, "ranking").join(g.vertices, "id").select("tier", "alt"))(graph(s, d, "w12a")))


_TIERS = f"{_closure(8, 'e', 'q1_', 'beat1')}, t1 AS MATERIALIZED (SELECT alt FROM n WHERE alt NOT IN (SELECT b FROM beat1))"
for _t in (2, 3):
    _gone = " UNION ALL ".join(f"SELECT alt FROM t{i}" for i in range(1, _t))
    _TIERS += f", gone{_t} AS ({_gone}), e{_t} AS MATERIALIZED (SELECT a, b, w FROM e WHERE a NOT IN (SELECT alt FROM gone{_t}) AND b NOT IN (SELECT alt FROM gone{_t}))"
    _TIERS += f", {_closure(8, f'e{_t}', f'q{_t}_', f'beat{_t}')}, t{_t} AS MATERIALIZED (SELECT alt FROM n WHERE alt NOT IN (SELECT alt FROM gone{_t}) AND alt NOT IN (SELECT b FROM beat{_t}) AND (SELECT count(*) FROM gone{_t}) < 3)"
_ALL_TIERS = " UNION ALL ".join(f"SELECT CAST({i} AS INT) AS tier, alt FROM t{i}" for i in (1, 2, 3))


@query(_sql("w12a", f", {_TIERS} {_ALL_TIERS}").replace("margin > 0) , ", "margin > 0), "))
def topk_remove(s, d):
    g = graph(s, d, "w12a")
    return rule.top_k(g, 3).join(g.vertices, "id").select("tier", "alt")


def _accepted_sql(rows: str, head: str) -> str:
    """CTE kept(ord, a, b, kept): rows(ord, a, b), ord from 1, taken in order unless b reaches a; what a vertex reaches is a bit mask in a list."""
    return (
        f"WITH RECURSIVE {head}, src AS MATERIALIZED ({rows}), "
        "ix AS MATERIALIZED (SELECT v, row_number() OVER (ORDER BY v) AS i FROM (SELECT a AS v FROM src UNION SELECT b FROM src)), "
        "todo AS MATERIALIZED (SELECT ord, a, b, x.i AS ia, y.i AS ib FROM src JOIN ix x ON x.v = a JOIN ix y ON y.v = b), "
        "st(ord, reach, kept) AS (SELECT CAST(0 AS BIGINT), (SELECT list(CAST(1 AS BIGINT) << CAST(i AS BIGINT) ORDER BY i) FROM ix), false UNION ALL "
        "SELECT t.ord, CASE WHEN (st.reach[ib] >> ia) & 1 = 0 THEN list_transform(st.reach, lambda r: CASE WHEN (r >> ia) & 1 = 1 THEN r | st.reach[ib] ELSE r END) ELSE st.reach END, (st.reach[ib] >> ia) & 1 = 0 "
        "FROM st JOIN todo t ON t.ord = st.ord + 1), kept AS MATERIALIZED (SELECT todo.ord, a, b, kept FROM todo JOIN st USING (ord)) "
    )


_PAIRS = "SELECT row_number() OVER (ORDER BY margin DESC, a, b) AS ord, a, b FROM m WHERE margin >= 0"
_KEPT_PAIRS = _accepted_sql(_PAIRS, f"{WORKLOADS['w12a'][1]}, {_MARGINS}")
_PAIR_RANKS = "SELECT alt, 1 + (SELECT count(*) FROM kept WHERE kept AND b = alt) AS rnk FROM n"


def _key_order(b: DataFrame) -> DataFrame:
    return b.select("alt").distinct().select("alt", F.col("alt").alias("pos"))


@query(_KEPT_PAIRS + _PAIR_RANKS)
def ranked_pairs_ranking(s, d):
    b = store(_nation_ballots(s, d), "ballots")
    return rankedpairs.ranked_pairs(mg.majority_margins(b), _key_order(b))


@query(_KEPT_PAIRS + "SELECT kept.a, kept.b, margin, kept FROM kept JOIN m ON m.a = kept.a AND m.b = kept.b WHERE kept")
def ranked_pairs_kept(s, d):
    b = store(_nation_ballots(s, d), "ballots")
    return rankedpairs.kept_pairs(mg.majority_margins(b), _key_order(b)).filter("kept")


@query(
    _accepted_sql(_PAIRS, f"{WORKLOADS['w12a'][1]}, {_MARGINS}, {_closure()}")
    + f", one AS ({_RANKING}), two AS ({_PAIR_RANKS}), s AS (SELECT sign(x.rnk - y.rnk) * sign(p.rnk - q.rnk) AS s FROM one x JOIN one y ON x.alt < y.alt JOIN two p ON p.alt = x.alt JOIN two q ON q.alt = y.alt) "
    "SELECT count(*) FILTER (s > 0) AS agree, count(*) FILTER (s < 0) AS disagree, count(*) FILTER (s = 0) AS tied FROM s"
)
def rule_agreement(s, d):
    b = store(_nation_ballots(s, d), "ballots")
    g = mg.graph_of(b)
    wpr = rule.ranking(paths.all_pairs_widest(g, "fw"), g.vertices).join(g.vertices, "id").select("alt", "rnk")
    return checks.kendall(wpr, rankedpairs.ranked_pairs(mg.majority_margins(b), _key_order(b)))


def _key_digraph(s: SparkSession, d: str) -> DataFrame:
    """(src, dst): every part-supplier pair of lineitem, from key to key; a part and a supplier of the same key are one vertex."""
    rows = load(s, d, "lineitem").select(F.col("l_partkey").cast("long").alias("src"), F.col("l_suppkey").cast("long").alias("dst"))
    return store(rows.filter("src <> dst").distinct(), "digraph")


def _trade(s: SparkSession, d: str) -> DataFrame:
    """(src, dst, q): quantities from supplier nations to the customer nations other than themselves."""
    t = {n: load(s, d, n) for n in ("lineitem", "orders", "customer", "supplier")}
    rows = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey")).join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
    return rows.filter("s_nationkey <> c_nationkey").groupBy(F.col("s_nationkey").cast("long").alias("src"), F.col("c_nationkey").cast("long").alias("dst")).agg(F.sum(F.col("l_quantity").cast("long")).alias("q"))


def _nation_digraph(s: SparkSession, d: str) -> DataFrame:
    """(ord, src, dst): trade from supplier nations to customer nations, the largest quantity first."""
    return number(_trade(s, d), [F.desc("q"), F.col("src"), F.col("dst")], "ord").select("ord", "src", "dst")


def _net_digraph(s: SparkSession, d: str) -> DataFrame:
    """(ord, src, dst): between two nations, numbered from 1, the trade that one has more, the largest first."""
    net = _trade(s, d).groupBy(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).agg(F.sum(F.when(F.col("src") < F.col("dst"), F.col("q")).otherwise(-F.col("q"))).alias("q")).filter("q <> 0")
    forth = F.col("q") > 0
    rows = net.select((1 + F.when(forth, F.col("x")).otherwise(F.col("y"))).alias("src"), (1 + F.when(forth, F.col("y")).otherwise(F.col("x"))).alias("dst"), F.abs("q").alias("q"))
    return number(rows, [F.desc("q"), F.col("src"), F.col("dst")], "ord").select("ord", "src", "dst")


_TRADE = (
    "SELECT row_number() OVER (ORDER BY q DESC, a, b) AS ord, a, b FROM (SELECT CAST(s_nationkey AS BIGINT) AS a, CAST(c_nationkey AS BIGINT) AS b, sum(CAST(l_quantity AS BIGINT)) AS q FROM lineitem "
    "JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey <> c_nationkey GROUP BY 1, 2)"
)


@query(_accepted_sql(_TRADE, "z AS (SELECT 1)") + "SELECT ord, a AS src, b AS dst, kept FROM kept")
def acyclic_subgraph_nations(s, d):
    return rankedpairs.emas(_nation_digraph(s, d))


@query()
def acyclic_subgraph(s, d):
    return rankedpairs.emas(_key_digraph(s, d).select(F.xxhash64("src", "dst").alias("ord"), "src", "dst"))


@query(
    "WITH RECURSIVE g AS (SELECT DISTINCT l_partkey AS a, l_suppkey AS b FROM lineitem WHERE l_partkey <> l_suppkey), r AS (SELECT CAST(0 AS BIGINT) AS v UNION SELECT b FROM g JOIN r ON a = v) "
    "SELECT EXISTS (SELECT 1 FROM r WHERE v = 13) AS winner, EXISTS (SELECT 1 FROM r WHERE v = 13) AS reachable"
)
def reduction_reachability(s, d):
    rows = _key_digraph(s, d)
    ends = s.createDataFrame([(0,), (13,)], "id long")
    vertices = store(rows.select(F.col("src").alias("id")).unionByName(rows.select(F.col("dst").alias("id"))).unionByName(ends).distinct(), "vertices")
    g = reductions.reachability_to_wpr(rows, vertices, 0, 13)
    g = PrefGraph(store(g.vertices, "vertices"), store(g.edges, "edges"))
    reach = components.reachable(PrefGraph(vertices.select(F.col("id").alias("alt"), "id"), rows.withColumn("w", F.lit(1))), 0, 13)
    return s.createDataFrame([(rule.is_winner(g, 0)[0], reach)], "winner boolean, reachable boolean")


_NET = (
    "SELECT row_number() OVER (ORDER BY q DESC, a, b) AS ord, a, b FROM (SELECT 1 + CAST(CASE WHEN q > 0 THEN x ELSE y END AS BIGINT) AS a, 1 + CAST(CASE WHEN q > 0 THEN y ELSE x END AS BIGINT) AS b, abs(q) AS q FROM ("
    "SELECT least(s_nationkey, c_nationkey) AS x, greatest(s_nationkey, c_nationkey) AS y, sum(CASE WHEN s_nationkey < c_nationkey THEN CAST(l_quantity AS BIGINT) ELSE -CAST(l_quantity AS BIGINT) END) AS q FROM lineitem "
    "JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey <> c_nationkey GROUP BY 1, 2) WHERE q <> 0)"
)
_PLACES = (2, 40, 120, 200)


@query(_accepted_sql(_NET, "z AS (SELECT 1)") + f"SELECT ord AS f, NOT kept AS zero_wins FROM kept WHERE ord IN {_PLACES}")
def reduction_acyclic_subgraph(s, d):
    """Net trade between nations, the largest first, as ranked pairs in which 0 wins where the edge of a place is not kept."""
    edges = store(_net_digraph(s, d), "digraph", n=F.count(F.lit(1)))
    return s.createDataFrame([(f, rankedpairs.is_winner(*reductions.emas_to_ranked_pairs(edges, f), 0)) for f in _PLACES if f <= edges.told["n"]], "f long, zero_wins boolean")


@query(_sql("w12d", "SELECT a, b, 2 * w AS margin FROM e"))
def realised_profile(s, d):
    """The margins of linear orders that realise twice the majority graph of event types."""
    g = graph(s, d, "w12d")
    ballots = store(reductions.realise_profile(PrefGraph(g.vertices, g.edges.withColumn("w", 2 * F.col("w")))), "ballots")
    return g.named(mg.majority_margins(ballots).filter("margin > 0"), "a", "b").select("a", "b", "margin")


@query()
def run_log(s, d):
    g = graph(s, d, "w4s")
    rows = [(k, n, x["kind"], x["undecided"], x.get("supersteps", 0)) for k, f in (("auto", {}), ("labels", {"strategy": "labels", "finish_threshold": 0})) for n, x in enumerate(wn.find_winners(g, **f).log)]
    return s.createDataFrame(rows, "strategy string, step int, kind string, undecided long, supersteps int")


@query()
def mallows_ballots(s, d):
    """A ballot for each customer, drawn around the order priorities by their sums of prices."""
    price = F.sum(F.col("o_totalprice").cast("decimal(18,2)"))
    order = store(number(load(s, d, "orders").groupBy(F.col("o_orderpriority").alias("priority")).agg(price.alias("x")), [F.desc("x"), F.col("priority")], "alt").select("alt", "priority"), "order", m=F.count(F.lit(1)))
    drawn = synth.mallows_of(load(s, d, "customer").select(F.col("c_custkey").alias("id")), order.told["m"], 0.7)
    return drawn.join(F.broadcast(order), "alt").select("voter", F.col("priority").alias("alt"), "rank", "weight")


@query()
def winners_mallows(s, d):
    g = mg.graph_of(store(synth.mallows(s, 200, 500, 0.98), "ballots"))
    return _named(g, wn.find_winners(g).winners)


@query()
def winners_sparse_synthetic(s, d):
    """10,000 vertices of low density."""
    g = synth.sparse_wmg(s, 10_000, 0.002)
    return wn.find_winners(PrefGraph(store(g.vertices, "vertices"), store(g.edges, "edges"))).winners


# ---- the other operators on ballots, winners and results ----------------------------------------


@query("WITH " + WORKLOADS["w4s"][1] + ", v AS (SELECT DISTINCT voter FROM b WHERE rank = 1 AND alt % 2 = 0) SELECT voter, alt, CAST(rank AS INT) AS rank, CAST(weight AS BIGINT) AS weight FROM b WHERE voter IN (SELECT voter FROM v) AND alt IN (SELECT s_suppkey FROM supplier WHERE s_acctbal > 0)")
def ballots_restricted(s, d):
    b = ballots_of("w4s")(s, d)
    return bl.restrict(b, b.filter("rank = 1 and alt % 2 = 0"), load(s, d, "supplier").filter("s_acctbal > 0").select(F.col("s_suppkey").alias("alt")))


@query("WITH " + WORKLOADS["w12d"][1] + " SELECT p || CAST(voter AS VARCHAR) AS voter, alt, CAST(rank AS INT) AS rank, CAST(1 AS BIGINT) AS weight FROM b, (VALUES ('1:'), ('2:')) AS x(p)")
def ballots_union(s, d):
    return bl.union(_event_ballots(s, d), _event_ballots(s, d))


@query(_sql("w4s", f"SELECT s_suppkey, s_name, s_nationkey FROM supplier WHERE s_suppkey IN ({_WON})", True))
def winners_described(s, d):
    g = graph(s, d, "w4s")
    return rule.describe(_named(g, wn.find_winners(g).winners), load(s, d, "supplier").select("s_suppkey", "s_name", "s_nationkey"), "s_suppkey")


@query("SELECT CAST(user_id AS VARCHAR) AS voter, CAST(1 + coalesce(sum(TRY_CAST(json_extract_string(props, '$.k') AS BIGINT)), 0) AS BIGINT) AS weight FROM events GROUP BY 1")
def weights_from_json(s, d):
    return bl.weight_from_json(load(s, d, "events"))


@query("WITH " + WORKLOADS["w3s"][1].replace("sc AS", "sc3 AS").replace("FROM sc)", "FROM sc3)").replace("b AS", "b3 AS") + ", " + WORKLOADS["w4s"][1] + " SELECT voter, alt, CAST(rank AS INT) AS rank, 'right' AS side FROM (SELECT voter, alt, rank FROM b EXCEPT ALL SELECT voter, alt, rank FROM b3)")
def ballots_diff(s, d):
    one, two = (ballots_of(w)(s, d).select("voter", "alt", "rank") for w in ("w3s", "w4s"))
    return checks.diff(one, two)


@query(_sql("w4s", f"SELECT count(*) AS edges, (SELECT count(*) FROM ({_WON})) AS winners, (SELECT count(*) FROM n) AS alternatives FROM e", True))
def sql_views(s, d):
    from .sql import register

    register(s, graph(s, d, "w4s"))
    return s.sql("SELECT (SELECT count(*) FROM wmg_edges) AS edges, (SELECT count(*) FROM wpr_winners) AS winners, (SELECT count(*) FROM wmg_vertices) AS alternatives")


@query("SELECT lang AS voter, source AS alt, CAST(rank() OVER (PARTITION BY lang ORDER BY sum(n_chars) DESC) AS INT) AS rank FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) GROUP BY 1, 2")
def ballots_documents_of_quality(s, d):
    good = load(s, d, "documents").join(load(s, d, "labels").filter("quality = 1"), "doc_id", "left_semi")
    return bl.from_scores(good.groupBy("lang", "source").agg(F.sum("n_chars").alias("n")), "lang", "source", "n").select("voter", "alt", "rank")


@query("WITH " + WORKLOADS["w12d"][1] + " SELECT fmt, alt, CAST(rank AS INT) AS rank, count(*) AS n FROM b, (VALUES ('json'), ('orc'), ('parquet')) AS x(fmt) GROUP BY 1, 2, 3")
def ballots_of_each_format(s, d):
    out, b = None, _event_ballots(s, d)
    for fmt in ("json", "orc", "parquet"):
        path = f"{shared_folder(s)}/ballots-{uuid.uuid4().hex}"
        b.write.format(fmt).save(path)
        rows = read_ballots(s, path, fmt).groupBy("alt", "rank").agg(F.count(F.lit(1)).alias("n")).select(F.lit(fmt).alias("fmt"), "alt", "rank", "n")
        out = rows if out is None else out.unionByName(rows)
    return out


@query(_sql("w12a", "SELECT 'init' AS kind, count(*) AS undecided FROM n LEFT JOIN (SELECT b, max(w) AS i FROM e GROUP BY 1) ON b = alt LEFT JOIN (SELECT a, max(w) AS o FROM e GROUP BY 1) ON a = alt WHERE coalesce(i, 0) <= coalesce(o, 0)"))
def log_written_and_read(s, d):
    path = f"{shared_folder(s)}/log-{uuid.uuid4().hex}"
    write_log([{"kind": x["kind"], "undecided": x["undecided"]} for x in wn.find_winners(graph(s, d, "w12a")).log], s, path)
    return s.read.schema("kind string, undecided long").json(path).filter("kind = 'init'")


_DAILY = "sc AS (SELECT CAST(user_id AS VARCHAR) || '@' || CAST(date_trunc('day', ts) AS VARCHAR) AS voter, event_type AS alt, count(*) AS score FROM events GROUP BY 1, 2)"


@query(f"WITH {_DAILY}, {_RANKED}, {_CO} SELECT a, b, CAST(c AS BIGINT) AS margin FROM c")
def stream_margins(s, d):
    """The margins after all micro-batches: one source file a batch, then a late row far ahead closes every window."""
    from .streaming import current_margins, margin_updates

    base = f"{shared_folder(s)}/stream-{uuid.uuid4().hex}"
    events = load(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    events.coalesce(1).write.parquet(f"{base}/in")
    margin_updates(s.readStream.schema(events.schema).parquet(f"{base}/in"), f"{base}/out", f"{base}/state").awaitTermination()
    events.limit(1).withColumn("ts", F.lit("2030-01-01").cast("timestamp")).coalesce(1).write.mode("append").parquet(f"{base}/in")
    margin_updates(s.readStream.schema(events.schema).parquet(f"{base}/in"), f"{base}/out", f"{base}/state").awaitTermination()
    return current_margins(s, f"{base}/out")


@query(f"WITH {WORKLOADS['w12d'][1]} SELECT x.alt AS above, y.alt AS below, count(*) AS n FROM b x JOIN b y ON x.voter = y.voter AND x.rank < y.rank GROUP BY 1, 2")
def sql_ballot_pairs(s, d):
    from .sql import BallotPairs

    s.udtf.register("ballot_pairs", BallotPairs)
    bl.nest(_event_ballots(s, d)).createOrReplaceTempView("nested_ballots")
    return s.sql("SELECT p.above, p.below, count(*) AS n FROM nested_ballots, LATERAL ballot_pairs(tiers) AS p GROUP BY 1, 2")
