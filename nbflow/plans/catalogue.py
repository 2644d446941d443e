"""The catalogue of wrangling operations on full tables, each with its SQL.

Sums of doubles go through decimals, so that both engines add up the same numbers.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from nbflow.operators import native as n
from nbflow.session import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def money(column: str):
    return F.sum(F.col(column).cast("decimal(18,4)")).cast("double")


def money_sql(column: str) -> str:
    return f"CAST(sum(CAST({column} AS DECIMAL(18,4))) AS DOUBLE)"


def _query(name: str, sql: str, *tables: str):
    """Registers a function of the named tables."""

    def keep(build):
        QUERIES[name] = lambda spark, d: build(*[table(spark, d, t) for t in tables])
        ORACLES[name] = sql
        return build

    return keep


def _holes(events):
    """Events with missing values: every seventh value, every eleventh type."""
    return events.select("event_id", "user_id", "ts", F.when(F.col("event_id") % 7 != 0, F.col("value")).alias("value"), F.when(F.col("event_id") % 11 != 0, F.col("event_type")).alias("event_type"))


HOLES = "(SELECT event_id, user_id, ts, CASE WHEN event_id % 7 <> 0 THEN value END AS value, CASE WHEN event_id % 11 <> 0 THEN event_type END AS event_type FROM events)"

_query("op_dropna", f"SELECT * FROM {HOLES} WHERE value IS NOT NULL AND event_type IS NOT NULL", "events")(lambda e: n.dropna(_holes(e), ["value", "event_type"]))
_query("op_dropna_all", f"SELECT * FROM {HOLES} WHERE value IS NOT NULL OR event_type IS NOT NULL", "events")(lambda e: n.dropna(_holes(e), ["value", "event_type"], how="all"))
_query("op_fillna", f"SELECT event_id, user_id, ts, coalesce(value, 0.0::DOUBLE) AS value, coalesce(event_type, 'unknown') AS event_type FROM {HOLES}", "events")(lambda e: n.fillna(_holes(e), {"value": 0.0, "event_type": "unknown"}))
_query("op_fill_mean", f"SELECT event_id, round(coalesce(value, (SELECT avg(value) FROM {HOLES})), 6) AS value FROM {HOLES}", "events")(lambda e: n.fill_mean(_holes(e), "value").select("event_id", F.round("value", 6).alias("value")))
_query("op_ffill", f"SELECT event_id, user_id, ts, last_value(value IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS value, event_type FROM {HOLES}", "events")(lambda e: n.ffill(_holes(e), "value", ["user_id"], ["ts", "event_id"]))
_LINE = ["l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
_query("op_drop_duplicates", f"SELECT * EXCLUDE (nth) FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY {', '.join(_LINE)}) AS nth FROM lineitem) WHERE nth = 1", "lineitem")(lambda t: n.drop_duplicates(t, ["l_orderkey", "l_linenumber"], _LINE))
_query("op_astype", "SELECT o_orderkey, try_cast(s AS DOUBLE) AS price, CAST(o_orderkey AS VARCHAR) AS key FROM (SELECT o_orderkey, CASE WHEN o_orderkey % 50 = 0 THEN 'n/a' ELSE CAST(CAST(o_totalprice AS DECIMAL(18,2)) AS VARCHAR) END AS s FROM orders)", "orders")(
    lambda o: n.astype(o.select("o_orderkey", F.when(F.col("o_orderkey") % 50 == 0, "n/a").otherwise(F.col("o_totalprice").cast("decimal(18,2)").cast("string")).alias("price"), F.col("o_orderkey").alias("key")), {"price": "double", "key": "string"})
)
_query("op_rename", "SELECT p_partkey AS key, p_name AS name, p_size FROM part", "part")(lambda p: n.rename(n.select(p, "p_partkey", "p_name", "p_size"), {"p_partkey": "key", "p_name": "name"}))
_query("op_drop_cols", "SELECT * EXCLUDE (p_name, p_type) FROM part", "part")(lambda p: n.drop_columns(p, "p_name", "p_type"))
_query("op_select", "SELECT p_partkey, p_brand FROM part", "part")(lambda p: n.select(p, "p_partkey", "p_brand"))
_query("op_filter", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > 40 AND l_returnflag IN ('A', 'R') AND l_discount BETWEEN 0.02 AND 0.05", "lineitem")(
    lambda t: n.query(t, (F.col("l_quantity") > 40) & F.col("l_returnflag").isin("A", "R") & F.col("l_discount").between(0.02, 0.05)).select("l_orderkey", "l_linenumber", "l_quantity")
)
_query("op_str_contains", "SELECT p_partkey, p_name FROM part WHERE contains(p_name, 'ring')", "part")(lambda p: n.query(p, F.col("p_name").contains("ring")).select("p_partkey", "p_name"))
_query("op_assign", "SELECT l_orderkey, l_linenumber, CAST(CAST(l_extendedprice AS DECIMAL(18,4)) * (1 - CAST(l_discount AS DECIMAL(18,4))) AS DOUBLE) AS revenue FROM lineitem", "lineitem")(
    lambda t: n.assign(t, revenue=(F.col("l_extendedprice").cast("decimal(18,4)") * (1 - F.col("l_discount").cast("decimal(18,4)"))).cast("double")).select("l_orderkey", "l_linenumber", "revenue")
)
_query("op_map_values", "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 'done' WHEN 'O' THEN 'open' END AS status FROM orders", "orders")(lambda o: n.map_values(o, "o_orderstatus", {"F": "done", "O": "open"}, "status").select("o_orderkey", "status"))
_query("op_replace", "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 'done' WHEN 'O' THEN 'open' ELSE o_orderstatus END AS o_orderstatus FROM orders", "orders")(lambda o: n.replace(o.select("o_orderkey", "o_orderstatus"), "o_orderstatus", {"F": "done", "O": "open"}))
_query("op_apply", "SELECT p_partkey, p_size * 2 + length(p_name) AS score FROM part", "part")(lambda p: n.apply_rows(p, "score", lambda size, name: size * 2 + len(name), "long", "p_size", "p_name").select("p_partkey", "score"))
_query("op_get_dummies", "SELECT o_orderkey, CAST(o_orderstatus = 'F' AS INT) AS \"o_orderstatus_F\", CAST(o_orderstatus = 'O' AS INT) AS \"o_orderstatus_O\", CAST(o_orderstatus = 'P' AS INT) AS \"o_orderstatus_P\" FROM orders", "orders")(lambda o: n.get_dummies(o.select("o_orderkey", "o_orderstatus"), "o_orderstatus"))
_query("op_cut", "SELECT p_partkey, CASE WHEN p_size > 0 AND p_size <= 10 THEN 0 WHEN p_size > 10 AND p_size <= 25 THEN 1 WHEN p_size > 25 AND p_size <= 50 THEN 2 END AS band FROM part", "part")(lambda p: n.cut(p, "p_size", [0, 10, 25, 50], "band").select("p_partkey", "band"))
_query("op_qcut", "SELECT c_custkey, CAST(len(list_filter((SELECT [quantile_cont(c_acctbal, 0.25), quantile_cont(c_acctbal, 0.5), quantile_cont(c_acctbal, 0.75)] FROM customer), lambda e: e < c_acctbal)) AS INT) AS quarter FROM customer", "customer")(lambda c: n.qcut(c, "c_acctbal", 4, "quarter").select("c_custkey", "quarter"))
_query("op_merge_inner", "SELECT o_orderkey, c_name, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey", "orders", "customer")(lambda o, c: n.merge(o, c, o.o_custkey == c.c_custkey).select("o_orderkey", "c_name", "c_mktsegment"))
_query("op_merge_left", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_totalprice > 400000) o ON o_custkey = c_custkey", "customer", "orders")(lambda c, o: n.merge(c, o.filter("o_totalprice > 400000"), F.expr("o_custkey = c_custkey"), "left").select("c_custkey", "o_orderkey"))
_query("op_merge_right", "SELECT p_partkey, l_orderkey FROM (SELECT * FROM lineitem WHERE l_quantity > 49) l RIGHT JOIN part ON l_partkey = p_partkey", "lineitem", "part")(lambda t, p: n.merge(t.filter("l_quantity > 49"), p, F.expr("l_partkey = p_partkey"), "right").select("p_partkey", "l_orderkey"))
_query("op_merge_outer", "SELECT s_suppkey, c_custkey FROM supplier FULL JOIN customer ON s_suppkey = c_custkey", "supplier", "customer")(lambda s, c: n.merge(s, c, F.expr("s_suppkey = c_custkey"), "outer").select("s_suppkey", "c_custkey"))
_query("op_merge_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", "customer", "orders")(lambda c, o: n.merge(c, o, F.expr("o_custkey = c_custkey"), "semi").select("c_custkey"))
_query("op_merge_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)", "customer", "orders")(lambda c, o: n.merge(c, o.filter("o_totalprice > 300000"), F.expr("o_custkey = c_custkey"), "anti").select("c_custkey"))
_query("op_merge_cross", "SELECT n_name, r_name FROM nation CROSS JOIN region", "nation", "region")(lambda a, r: n.merge(a, r, [], "cross").select("n_name", "r_name"))
_query(
    "op_merge_asof",
    """SELECT p.event_id, p.user_id, p.ts, (SELECT v.event_id FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts ORDER BY v.ts DESC LIMIT 1) AS seen
       FROM events p WHERE p.event_type = 'purchase'""",
    "events",
)(lambda e: n.merge_asof(e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.filter("event_type = 'view'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("view_id")), "user_id", "ts", "at", "view_id", "seen"))
_query("op_concat", "SELECT c_custkey AS key, c_name AS name, c_mktsegment AS segment FROM customer UNION ALL SELECT s_suppkey, s_name, NULL FROM supplier", "customer", "supplier")(
    lambda c, s: n.concat(c.select(F.col("c_custkey").alias("key"), F.col("c_name").alias("name"), F.col("c_mktsegment").alias("segment")), s.select(F.col("s_suppkey").alias("key"), F.col("s_name").alias("name")))
)
_query("op_groupby_agg", f"SELECT l_returnflag, l_linestatus, count(*) AS n, {money_sql('l_quantity')} AS quantity, min(l_extendedprice) AS least, max(l_extendedprice) AS most FROM lineitem GROUP BY ALL", "lineitem")(
    lambda t: n.groupby_agg(t, ["l_returnflag", "l_linestatus"], n=F.count("*"), quantity=money("l_quantity"), least=F.min("l_extendedprice"), most=F.max("l_extendedprice"))
)
_query("op_transform", "SELECT o_orderkey, max(o_totalprice) OVER (PARTITION BY o_custkey) AS best FROM orders", "orders")(lambda o: n.transform(o, ["o_custkey"], F.max("o_totalprice"), "best").select("o_orderkey", "best"))
_PIVOT = ", ".join(f"CAST(sum(CASE WHEN o_orderpriority = '{p}' THEN CAST(o_totalprice AS DECIMAL(18,4)) END) AS DOUBLE) AS \"{p}\"" for p in ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"))
_query("op_pivot_table", f"SELECT o_orderstatus, {_PIVOT} FROM orders GROUP BY o_orderstatus", "orders")(lambda o: n.pivot_table(o, ["o_orderstatus"], "o_orderpriority", money("o_totalprice")))
_CROSS = ", ".join(f"count(*) FILTER (WHERE o_orderpriority = '{p}') AS \"{p}\"" for p in ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"))
_query("op_crosstab", f"SELECT o_orderstatus, {_CROSS} FROM orders GROUP BY o_orderstatus", "orders")(lambda o: n.crosstab(o, "o_orderstatus", "o_orderpriority"))
_query("op_melt", "SELECT p_partkey, 'p_size' AS variable, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part", "part")(lambda p: n.melt(p.withColumn("p_size", F.col("p_size").cast("double")), ["p_partkey"], ["p_size", "p_retailprice"]))
_query("op_stack", f"SELECT * FROM (SELECT event_id, 'event_type' AS field, event_type AS content FROM {HOLES} UNION ALL SELECT event_id, 'user', CASE WHEN user_id % 5 <> 0 THEN CAST(user_id AS VARCHAR) END FROM {HOLES}) WHERE content IS NOT NULL", "events")(
    lambda e: n.stack(_holes(e).withColumn("user", F.when(F.col("user_id") % 5 != 0, F.col("user_id").cast("string"))), ["event_id"], ["event_type", "user"], "field", "content")
)
_query("op_unstack", "SELECT o_custkey, max(CASE WHEN o_orderstatus = 'F' THEN k END) AS \"F\", max(CASE WHEN o_orderstatus = 'O' THEN k END) AS \"O\" FROM (SELECT o_custkey, o_orderstatus, max(o_orderkey) AS k FROM orders GROUP BY ALL) GROUP BY o_custkey", "orders")(
    lambda o: n.unstack(o.groupBy("o_custkey", "o_orderstatus").agg(F.max("o_orderkey").alias("k")), ["o_custkey"], "o_orderstatus", "k", ["F", "O"])
)
_query("op_sort", "SELECT o_orderkey, o_totalprice, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS nth FROM orders", "orders")(lambda o: n.sorted_places(o.select("o_orderkey", "o_totalprice"), [F.col("o_totalprice").desc(), F.col("o_orderkey")], "nth"))
_query("op_nlargest", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10", "orders")(lambda o: n.nlargest(o, 10, "o_totalprice", "o_orderkey").select("o_orderkey", "o_totalprice"))
_query("op_head", "SELECT p_partkey, p_name FROM part ORDER BY p_partkey LIMIT 5", "part")(lambda p: n.head(p, 5, "p_partkey").select("p_partkey", "p_name"))
_query("op_tail", "SELECT p_partkey, p_name FROM part ORDER BY p_partkey DESC LIMIT 5", "part")(lambda p: n.tail(p, 5, "p_partkey").select("p_partkey", "p_name"))
_ALONG = (["user_id"], ["ts", "event_id"])
_W = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"
_query("op_rank", "SELECT event_id, CAST(rank() OVER (PARTITION BY user_id ORDER BY value) AS INT) AS r, CAST(dense_rank() OVER (PARTITION BY user_id ORDER BY value) AS INT) AS d FROM events", "events")(lambda e: n.along(e, ["user_id"], ["value"], r=lambda w: F.rank().over(w), d=lambda w: F.dense_rank().over(w)).select("event_id", "r", "d"))
_query("op_shift", f"SELECT event_id, lag(value, 2) {_W} AS was FROM events", "events")(lambda e: n.shift(e, "value", 2, *_ALONG, "was").select("event_id", "was"))
_query("op_diff", f"SELECT event_id, round(value - lag(value) {_W}, 6) AS step FROM events", "events")(lambda e: n.diff(e, "value", *_ALONG, "step").select("event_id", F.round("step", 6).alias("step")))
_query("op_pct_change", f"SELECT event_id, round((value - lag(value) {_W}) / nullif(lag(value) {_W}, 0), 6) AS rate FROM events", "events")(lambda e: n.pct_change(e, "value", *_ALONG, "rate").select("event_id", F.round("rate", 6).alias("rate")))
_query("op_cumsum", "SELECT event_id, CAST(sum(CAST(value AS DECIMAL(18,4))) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS total FROM events", "events")(lambda e: n.cumsum(e.withColumn("value", F.col("value").cast("decimal(18,4)")), "value", *_ALONG, "total").select("event_id", F.col("total").cast("double").alias("total")))
_query("op_rolling", "SELECT event_id, CAST(sum(CAST(value AS DECIMAL(18,4))) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING) AS DOUBLE) AS last3 FROM events", "events")(lambda e: n.rolling(e.withColumn("value", F.col("value").cast("decimal(18,4)")), F.sum("value"), 3, *_ALONG, "last3").select("event_id", F.col("last3").cast("double").alias("last3")))
_query("op_resample", f"SELECT date_trunc('day', ts) AS ts, count(*) AS n, {money_sql('value')} AS total FROM events GROUP BY 1", "events")(lambda e: n.resample(e, "ts", "day", n=F.count("*"), total=money("value")).withColumn("ts", F.col("ts").cast("timestamp_ntz")))
_query("op_dt_parts", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS year, CAST(month(o_orderdate) AS INT) AS month, CAST(quarter(o_orderdate) AS INT) AS quarter, CAST(dayofyear(o_orderdate) AS INT) AS dayofyear FROM orders", "orders")(lambda o: n.date_parts(o.select("o_orderkey", "o_orderdate"), "o_orderdate", "year", "month", "quarter", "dayofyear").drop("o_orderdate"))
_query("op_str_ops", "SELECT p_partkey, upper(p_name) AS up, CAST(length(p_name) AS INT) AS n, split_part(p_name, ' ', 1) AS head, replace(p_name, ' ', '_') AS snake, regexp_extract(p_brand, '([0-9]+)', 1) AS number FROM part", "part")(
    lambda p: p.select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").alias("n"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("head"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("snake"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("number"))
)
_query("op_explode", "SELECT doc_id, word FROM (SELECT doc_id, unnest(regexp_extract_all(text, '[^ \\t\\n\\r\\f\\v]+')) AS word FROM documents)", "documents")(lambda d: d.select("doc_id", F.explode(F.regexp_extract_all("text", F.lit(r"([^ \t\n\r\f\x0B]+)"), 1)).alias("word")))
_query("op_json_norm", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", "events")(lambda e: n.json_normalize(e.select("event_id", "props"), "props", "k long"))
_query("op_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem", "lineitem")(lambda t: t.agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")))
_query("op_describe", "SELECT count(c_acctbal) AS count, round(avg(c_acctbal), 4) AS mean, round(stddev_samp(c_acctbal), 4) AS std, min(c_acctbal) AS min, quantile_cont(c_acctbal, 0.5) AS median, max(c_acctbal) AS max FROM customer", "customer")(lambda c: n.describe(c, "c_acctbal").withColumns({x: F.round(x, 4) for x in ("mean", "std")}))
_query("op_value_counts", "SELECT c_mktsegment, count(*) AS count FROM customer GROUP BY 1", "customer")(lambda c: n.value_counts(c, "c_mktsegment"))
_query("op_nunique", "SELECT count(DISTINCT o_custkey) AS n FROM orders", "orders")(lambda o: o.agg(F.count_distinct("o_custkey").alias("n")))
for _name, _op in (("add", "+"), ("sub", "-"), ("mul", "*"), ("div", "/")):
    _value = f"a.v {_op} nullif(b.w, 0)" if _op == "/" else f"a.v {_op} b.w"
    _query(
        f"op_arith_{_name}",
        f"SELECT k, round({_value}, 6) AS out FROM (SELECT o_custkey AS k, count(*)::DOUBLE AS v FROM orders GROUP BY 1) a JOIN (SELECT c_custkey AS k, (c_nationkey)::DOUBLE AS w FROM customer) b USING (k)",
        "orders",
        "customer",
    )(lambda o, c, op=_op: n.arithmetic(o.groupBy(F.col("o_custkey").alias("k")).agg(F.count("*").cast("double").alias("v")), c.select(F.col("c_custkey").alias("k"), F.col("c_nationkey").cast("double").alias("w")), "k", "v", "w", op, "out").withColumn("out", F.round("out", 6)))
_query("op_sample", "SELECT o_orderkey FROM orders ORDER BY md5('s' || CAST(o_orderkey AS VARCHAR)), o_orderkey LIMIT 50", "orders")(lambda o: n.sample(o.select("o_orderkey"), 50, "o_orderkey", "s"))
_query("op_set_index", "SELECT o_custkey AS idx, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS INT) AS nth FROM orders", "orders")(lambda o: n.along(o.select(F.col("o_custkey").alias("idx"), "o_orderkey"), ["idx"], ["o_orderkey"], nth=lambda w: F.row_number().over(w)))
_PROFILE = " UNION ALL ".join(f"SELECT '{c}' AS \"column\", '{k}' AS kind, count(*) - count({c}) AS nulls, count(DISTINCT {c}) AS distinct_values, CAST(min({c}) AS VARCHAR) AS least, CAST(max({c}) AS VARCHAR) AS greatest FROM part" for c, k in (("p_partkey", "bigint"), ("p_brand", "string"), ("p_size", "int")))
_query("c8_profile", _PROFILE, "part")(lambda p: n.profile_frame(p, ["p_partkey", "p_brand", "p_size"]))
_query("w8_case", "SELECT o_orderkey, o_totalprice AS price, CAST(o_orderstatus = 'F' AS INT) AS \"status_F\", CAST(o_orderstatus = 'O' AS INT) AS \"status_O\", CAST(o_orderstatus = 'P' AS INT) AS \"status_P\" FROM orders", "orders")(
    lambda o: n.get_dummies(n.rename(o.select("o_orderkey", "o_totalprice", "o_orderstatus"), {"o_totalprice": "price", "o_orderstatus": "status"}), "status", ["F", "O", "P"])
)
