"""Joins, aggregates, windows, set operations and functions around the methods, each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from nbflow.operators import native
from nbflow.operators import relational as r
from nbflow.plans import catalogue
from nbflow.plans.catalogue import HOLES, _holes, money, money_sql
from nbflow.session import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _query(name: str, sql: str, *tables: str):
    def keep(build):
        QUERIES[name] = lambda spark, d: build(*[table(spark, d, t) for t in tables])
        ORACLES[name] = sql
        return build

    return keep


def _by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_O = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"

# --- windows
_query("win_row_number", f"SELECT event_id, CAST(row_number() {_O} AS INT) AS pos FROM events", "events")(lambda e: e.select("event_id", F.row_number().over(_by_user()).alias("pos")))
_query("win_rank", "SELECT event_type, n, CAST(rank() OVER (ORDER BY n DESC) AS INT) AS r, CAST(dense_rank() OVER (ORDER BY n DESC) AS INT) AS d FROM (SELECT event_type, count(*) AS n FROM events GROUP BY 1)", "events")(
    lambda e: r.ranked_counts(e, "event_type")
)
_query("win_lag_lead", f"SELECT event_id, date_diff('microsecond', lag(ts) {_O}, ts) AS since, lead(event_type) {_O} AS upcoming FROM events", "events")(
    lambda e: e.select("event_id", F.expr("timestampdiff(MICROSECOND, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts)").alias("since"), F.lead("event_type").over(_by_user()).alias("upcoming"))
)
_query("win_running", f"SELECT event_id, count(CASE WHEN event_type = 'signup' THEN 1 END) {_O} AS life_no, count(CASE WHEN event_type = 'click' THEN 1 END) {_O} AS wrangles FROM events", "events")(
    lambda e: e.select("event_id", F.count_if(F.col("event_type") == "signup").over(_by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("life_no"), F.count_if(F.col("event_type") == "click").over(_by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("wrangles"))
)
_query("win_range", "SELECT event_id, count(CASE WHEN event_type = 'click' THEN 1 END) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 21600000000 PRECEDING AND CURRENT ROW) AS recent FROM events", "events")(
    lambda e: e.select("event_id", F.count_if(F.col("event_type") == "click").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-21600000000, 0)).alias("recent"))
)
_query("win_ntile", "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_custkey) AS INT) AS q, percent_rank() OVER (PARTITION BY c_mktsegment ORDER BY c_custkey) AS p, cume_dist() OVER (PARTITION BY c_mktsegment ORDER BY c_custkey) AS c FROM customer", "customer")(
    lambda c: c.select("c_custkey", *[f.over(Window.partitionBy("c_mktsegment").orderBy("c_custkey")).alias(a) for f, a in ((F.ntile(4), "q"), (F.percent_rank(), "p"), (F.cume_dist(), "c"))])
)
_query("win_first_last", f"SELECT event_id, first_value(value IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS f, last_value(value IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS l FROM {HOLES}", "events")(
    lambda e: _holes(e).select("event_id", F.first("value", True).over(_by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("f"), F.last("value", True).over(_by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("l"))
)
_query(
    "win_gap_island",
    "SELECT conv_id, min(turn) AS first_turn, max(turn) AS last_turn, count(*) AS n FROM (SELECT *, turn - row_number() OVER (PARTITION BY conv_id, role = 'assistant' ORDER BY turn) AS island FROM conversations) WHERE role <> 'assistant' GROUP BY conv_id, island",
    "conversations",
)(lambda c: r.islands(c.withColumn("kind", F.col("role") == "assistant"), ["conv_id", "kind"], "turn").filter("not kind").groupBy("conv_id", "island").agg(F.min("turn").alias("first_turn"), F.max("turn").alias("last_turn"), F.count("*").alias("n")).drop("island"))
_query(
    "win_sessions",
    f"SELECT user_id, min(ts) AS began, max(ts) AS ended, count(*) AS n FROM (SELECT *, sum(fresh) {_O} AS s FROM (SELECT *, CASE WHEN lag(ts) {_O} IS NULL OR ts - lag(ts) {_O} > INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s",
    "events",
)(lambda e: r.sessions(e, "user_id", "ts", "event_id", "6 HOURS"))

# --- aggregates
_query("agg_hash", "SELECT user_id, event_type, count(*) AS n, count(DISTINCT props) AS d FROM events GROUP BY ALL", "events")(lambda e: e.groupBy("user_id", "event_type").agg(F.count("*").alias("n"), F.count_distinct("props").alias("d")))
_query("agg_distinct", "SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS types, count(DISTINCT (user_id, event_type)) AS both FROM events", "events")(lambda e: e.agg(F.count_distinct("user_id").alias("users"), F.count_distinct("event_type").alias("types"), F.count_distinct(F.struct("user_id", "event_type")).alias("both")))
_query("agg_collect", "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM conversations GROUP BY 1", "conversations")(lambda c: c.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",").alias("roles")))
_SALES = "(SELECT r_name, n_name, c_mktsegment, c_acctbal FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"


def _sales(c, n, g):
    return c.join(F.broadcast(n), F.expr("c_nationkey = n_nationkey")).join(F.broadcast(g), F.expr("n_regionkey = r_regionkey"))


for _kind in ("rollup", "cube"):
    _query(f"agg_{_kind}", f"SELECT r_name, c_mktsegment, CAST(grouping(r_name) AS INT) AS g, count(*) AS n, {money_sql('c_acctbal')} AS total FROM {_SALES} GROUP BY {_kind}(r_name, c_mktsegment)", "customer", "nation", "region")(
        lambda c, n, g, kind=_kind: getattr(_sales(c, n, g), kind)("r_name", "c_mktsegment").agg(F.grouping("r_name").cast("int").alias("g"), F.count("*").alias("n"), money("c_acctbal").alias("total"))
    )
_query("agg_grouping_sets", f"SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM {_SALES} GROUP BY GROUPING SETS ((r_name, c_mktsegment), (n_name), ())", "customer", "nation", "region")(
    lambda c, n, g: _sales(c, n, g).groupingSets([["r_name", "c_mktsegment"], ["n_name"], []], "r_name", "n_name", "c_mktsegment").agg(F.count("*").alias("n"))
)
_query("agg_filter", "SELECT count(*) AS all_docs, count(*) FILTER (WHERE lang = 'en') AS english, count(*) FILTER (WHERE n_chars > 1000) AS long_docs FROM documents", "documents")(lambda d: d.agg(F.count("*").alias("all_docs"), F.count_if(F.col("lang") == "en").alias("english"), F.count_if(F.col("n_chars") > 1000).alias("long_docs")))
_query("agg_percentile", "SELECT quantile_cont(n_chars, 0.5) AS p50, quantile_cont(n_chars, 0.9) AS p90 FROM documents", "documents")(lambda d: d.agg(F.percentile("n_chars", 0.5).alias("p50"), F.percentile("n_chars", 0.9).alias("p90")))
_query("agg_mode", "SELECT p_type FROM (SELECT p_type, count(*) AS n FROM part GROUP BY 1 ORDER BY n DESC, p_type LIMIT 1)", "part")(lambda p: p.groupBy("p_type").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "p_type").limit(1).select("p_type"))
_query("agg_stats", "SELECT p_type, round(stddev_samp(p_retailprice), 4) AS s, round(var_pop(p_size), 4) AS v, round(corr(p_size, p_retailprice), 4) AS c FROM part GROUP BY 1", "part")(lambda p: p.groupBy("p_type").agg(F.round(F.stddev_samp("p_retailprice"), 4).alias("s"), F.round(F.var_pop("p_size"), 4).alias("v"), F.round(F.corr("p_size", "p_retailprice"), 4).alias("c")))
_query("agg_approx", "SELECT true AS close", "documents")(lambda d: d.agg((F.abs(F.approx_count_distinct("text", 0.02) - F.count_distinct("text")) <= 0.1 * F.count_distinct("text")).alias("close")))

# --- sets
_WORDS = "SELECT DISTINCT p_name FROM part WHERE {}"


def _vocabulary(p, condition):
    return p.filter(condition).select("p_name")


_LEFT, _RIGHT = "p_size < 3", "p_retailprice > 995"
_query("set_union", f"{_WORDS.format(_LEFT)} UNION {_WORDS.format(_RIGHT)}", "part")(lambda p: _vocabulary(p, _LEFT).union(_vocabulary(p, _RIGHT)).distinct())
_query("set_union_all", "SELECT s_nationkey AS k FROM supplier UNION ALL SELECT n_nationkey FROM nation", "supplier", "nation")(lambda s, n: s.select(F.col("s_nationkey").alias("k")).union(n.select("n_nationkey")))
_query("set_intersect", f"{_WORDS.format(_LEFT)} INTERSECT {_WORDS.format(_RIGHT)}", "part")(lambda p: _vocabulary(p, _LEFT).intersect(_vocabulary(p, _RIGHT)))
_query("set_except", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT c_nationkey FROM customer WHERE c_acctbal > 9700", "nation", "customer")(lambda n, c: n.select(F.col("n_nationkey").alias("k")).subtract(c.filter("c_acctbal > 9700").select("c_nationkey")))
_query("set_except_all", "SELECT l_orderkey, l_linenumber FROM lineitem EXCEPT ALL SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem", "lineitem")(lambda t: t.select("l_orderkey", "l_linenumber").exceptAll(t.select("l_orderkey", "l_linenumber").distinct()))

# --- joins
_query("j_theta", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON a.source = b.source AND a.n_chars < b.n_chars AND b.n_chars - a.n_chars <= 20", "documents")(lambda d: r.band_join(d.select("source", F.col("doc_id").alias("a"), F.col("n_chars").alias("x")), d.select("source", F.col("doc_id").alias("b"), F.col("n_chars").alias("y")), "source", "x", "y", 20).select("a", "b"))
_query("j_range", "SELECT s.user_id, s.began, count(e.event_id) AS views FROM (SELECT user_id, date_trunc('day', ts) AS began FROM events GROUP BY ALL) s JOIN events e ON e.user_id = s.user_id AND e.ts >= s.began AND e.ts < s.began + INTERVAL 1 DAY AND e.event_type = 'view' GROUP BY ALL", "events")(
    lambda e: e.select("user_id", F.date_trunc("day", F.col("ts")).cast("timestamp_ntz").alias("began")).distinct().join(e.filter("event_type = 'view'").select("user_id", "ts", "event_id"), "user_id").filter("ts >= began and ts < began + interval 1 day").groupBy("user_id", "began").agg(F.count("event_id").alias("views"))
)
_query("j_interval", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR", "events")(
    lambda e: e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("purchase")).join(e.filter("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click")), "user_id").filter("ts <= at and ts >= at - interval 1 hour").select("purchase", "click")
)
_query("j_skew", "SELECT l_orderkey, l_linenumber, p_name FROM lineitem JOIN part ON l_partkey = p_partkey", "lineitem", "part")(lambda t, p: r.salted_join(t.select("l_orderkey", "l_linenumber", F.col("l_partkey").alias("k")), p.select(F.col("p_partkey").alias("k"), "p_name"), "k", 8).select("l_orderkey", "l_linenumber", "p_name"))
_query("sort_multi", "SELECT o_orderkey, o_orderpriority, row_number() OVER (ORDER BY o_orderpriority, o_totalprice DESC NULLS LAST, o_orderkey) AS nth FROM orders", "orders")(lambda o: native.sorted_places(o.select("o_orderkey", "o_orderpriority", "o_totalprice"), [F.col("o_orderpriority"), F.col("o_totalprice").desc_nulls_last(), F.col("o_orderkey")], "nth").drop("o_totalprice"))
_query("limit_offset", "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 10 OFFSET 20", "part")(lambda p: p.orderBy("p_partkey").offset(20).limit(10).select("p_partkey"))
_query("topk_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM orders) WHERE n <= 3", "orders")(lambda o: r.top_per_group(o, ["o_custkey"], [F.col("o_totalprice").desc(), "o_orderkey"], 3).select("o_custkey", "o_orderkey"))

# --- subqueries
_query("subq_scalar", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT max(s_acctbal) * 0.9 FROM supplier)", "customer", "supplier")(lambda c, s: c.filter(F.col("c_acctbal") > s.agg(F.max("s_acctbal") * 0.9).scalar()).select("c_custkey"))
_query("subq_exists", "SELECT DISTINCT user_id FROM events e WHERE event_type = 'signup' AND EXISTS (SELECT 1 FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.value > 50)", "events")(
    lambda e: e.filter("event_type = 'signup'").select("user_id").distinct().join(e.filter("event_type = 'purchase' and value > 50").select("user_id"), "user_id", "left_semi")
)
_query("subq_lateral", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1)", "customer", "orders")(lambda c, o: c.join(o.groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.min_by("o_orderkey", F.struct(-F.col("o_totalprice"), F.col("o_orderkey"))).alias("o_orderkey")), "c_custkey").select("c_custkey", "o_orderkey"))


def _recursive(spark, d):
    """Clicks from one to the next of a user within the hour, and how many hops each is from one that none precedes."""
    steps = table(spark, d, "events").filter("event_type = 'click'").selectExpr("event_id", "user_id", "ts", "lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev", "lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before")
    steps.selectExpr("event_id", "CASE WHEN before >= ts - INTERVAL 1 HOUR THEN prev END AS prev").createOrReplaceTempView("nbflow_steps")
    return spark.sql("WITH RECURSIVE hop(event_id, n) AS (SELECT event_id, 0 FROM nbflow_steps WHERE prev IS NULL UNION ALL SELECT s.event_id, n + 1 FROM hop h JOIN nbflow_steps s ON s.prev = h.event_id) SELECT event_id, n FROM hop")


_STEPS = "SELECT event_id, CASE WHEN lag(ts) OVER w >= ts - INTERVAL 1 HOUR THEN lag(event_id) OVER w END AS prev FROM events WHERE event_type = 'click' WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"
QUERIES["cte_recursive"] = _recursive
ORACLES["cte_recursive"] = f"WITH RECURSIVE steps AS ({_STEPS}), hop(event_id, n) AS (SELECT event_id, 0 FROM steps WHERE prev IS NULL UNION ALL SELECT s.event_id, n + 1 FROM hop h JOIN steps s ON s.prev = h.event_id) SELECT event_id, n FROM hop"

# --- functions
_query("fn_string", "SELECT conv_id, turn, lower(role) AS lo, trim('  ' || role || ' ') AS tr, CAST(levenshtein(role, 'user') AS INT) AS lev, md5(text) AS digest, role || '-' || CAST(turn AS VARCHAR) AS joined, substr(role, 2, 3) AS part, CAST(instr(role, 's') AS INT) AS at, translate(role, 'su', 'SU') AS tl, regexp_replace(role, '[aeiou]', '*', 'g') AS rx FROM conversations", "conversations")(
    lambda c: c.select("conv_id", "turn", F.lower("role").alias("lo"), F.trim(F.concat(F.lit("  "), "role", F.lit(" "))).alias("tr"), F.levenshtein("role", F.lit("user")).alias("lev"), F.md5("text").alias("digest"), F.concat_ws("-", "role", F.col("turn").cast("string")).alias("joined"), F.substring("role", 2, 3).alias("part"), F.instr("role", "s").alias("at"), F.translate("role", "su", "SU").alias("tl"), F.regexp_replace("role", "[aeiou]", "*").alias("rx"))
)
_query("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, date_trunc('month', o_orderdate)::TIMESTAMP AS m, CAST(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS INT) AS days, (o_orderdate + INTERVAL 10 DAY)::TIMESTAMP AS later FROM orders", "orders")(
    lambda o: o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m"), F.date_diff("o_orderdate", F.lit("1992-01-01").cast("date")).alias("days"), (F.col("o_orderdate") + F.expr("interval 10 days")).alias("later"))
)
_query("fn_math", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS a, round(exp(l_discount), 6) AS b, round(sqrt(l_quantity), 6) AS c, round(power(l_quantity, 1.5), 3) AS d, l_orderkey % 7 AS e, greatest(l_discount, l_tax) AS f, least(l_discount, l_tax) AS g FROM lineitem", "lineitem")(
    lambda t: t.select("l_orderkey", "l_linenumber", F.round(F.ln("l_extendedprice"), 6).alias("a"), F.round(F.exp("l_discount"), 6).alias("b"), F.round(F.sqrt("l_quantity"), 6).alias("c"), F.round(F.pow("l_quantity", F.lit(1.5)), 3).alias("d"), F.pmod("l_orderkey", F.lit(7)).alias("e"), F.greatest("l_discount", "l_tax").alias("f"), F.least("l_discount", "l_tax").alias("g"))
)
_query("fn_array", "SELECT vec_id, CAST(len(embedding) AS INT) AS n, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive, embedding[1:3] AS head, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm FROM embeddings", "embeddings")(
    lambda v: v.select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.slice("embedding", 1, 3).alias("head"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x), 4).alias("norm"))
)
_query("fn_map", "SELECT user_id, event_type AS key, count(*) AS value FROM events GROUP BY ALL HAVING count(*) > 10", "events")(
    lambda e: e.groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.explode(F.map_filter("m", lambda k, v: v > 10)))
)
_query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, CAST(json_extract(props, '$.k') AS BIGINT) * 2 AS twice, CAST(json_extract(props, '$.z') AS BIGINT) AS none FROM events", "events")(
    lambda e: e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), (F.from_json("props", "k long")["k"] * 2).alias("twice"), F.try_variant_get(F.parse_json("props"), "$.z", "long").alias("none"))
)
_query("fn_null", f"SELECT event_id, coalesce(value, -1.0) AS a, nullif(event_type, 'view') AS b, CASE WHEN value IS NOT NULL THEN 'has' ELSE 'none' END AS c, event_type IS NOT DISTINCT FROM NULL AS d, try_cast(event_type AS INT) AS e, value / nullif(user_id % 3, 0) AS f FROM {HOLES}", "events")(
    lambda e: _holes(e).select("event_id", F.coalesce("value", F.lit(-1.0)).alias("a"), F.nullif("event_type", F.lit("view")).alias("b"), F.nvl2("value", F.lit("has"), F.lit("none")).alias("c"), F.col("event_type").eqNullSafe(F.lit(None)).alias("d"), F.expr("try_cast(event_type AS INT)").alias("e"), F.try_divide("value", F.col("user_id") % 3).alias("f"))
)

#: The same query under the name of the operator that it shows.
ALIASES = {
    "j_inner": "op_merge_inner",
    "j_left": "op_merge_left",
    "j_right": "op_merge_right",
    "j_full": "op_merge_outer",
    "j_semi": "op_merge_semi",
    "j_anti": "op_merge_anti",
    "j_cross": "op_merge_cross",
    "j_asof": "op_merge_asof",
    "op_reset_index": "op_set_index",
    "win_dense_rank": "op_rank",
}
for _alias, _of in ALIASES.items():
    QUERIES[_alias], ORACLES[_alias] = catalogue.QUERIES[_of], catalogue.ORACLES[_of]
for _alias in ("win_percent_rank", "win_cume_dist"):
    QUERIES[_alias], ORACLES[_alias] = QUERIES["win_ntile"], ORACLES["win_ntile"]
