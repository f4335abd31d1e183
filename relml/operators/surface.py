"""The ordinary operators that users of the learners need, each with its oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query, sig, sig_sql
from ..functions.udx import ExplodePairs, gram_by, predictor
from ..sources.io import load
from ..datasets import period

c = F.col


def T(name: str):
    return lambda spark, sf: load(spark, sf, name)


line, orders, cust, part, supp, ev = (T(n) for n in ("lineitem", "orders", "customer", "part", "supplier", "events"))


def add(name: str, sql: str, fn) -> None:
    query(name, sql)(fn)


add("scan_parquet", "SELECT * FROM nation", lambda s, d: load(s, d, "nation"))
add("project_derived", f"SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice * (1 - l_discount) AS net FROM lineitem", lambda s, d: line(s, d).select("l_orderkey", "l_linenumber", "l_partkey", (c("l_extendedprice") * (1 - c("l_discount"))).alias("net")))
add("filter_train_period", "SELECT CAST(count(*) AS BIGINT) AS n FROM lineitem WHERE l_shipdate <= (SELECT max(l_shipdate) - INTERVAL 1 MONTH FROM lineitem)", lambda s, d: line(s, d).where(period(s, d, "train")["lineitem"]).agg(F.count("*").alias("n")))
add("split_last_month", "SELECT l_shipdate > (SELECT max(l_shipdate) - INTERVAL 1 MONTH FROM lineitem) AS test, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY 1", lambda s, d: line(s, d).groupBy(F.expr(period(s, d, "test")["lineitem"]).alias("test")).agg(F.count("*").alias("n")))
add("filter_predicates", "SELECT CAST(count(*) AS BIGINT) AS n FROM part WHERE p_size BETWEEN 5 AND 20 AND p_type IN (SELECT min(p_type) FROM part) AND p_name LIKE '%a%' AND p_brand IS NOT NULL", lambda s, d: part(s, d).where(c("p_size").between(5, 20) & c("p_name").like("%a%") & c("p_brand").isNotNull()).join(part(s, d).agg(F.min("p_type").alias("p_type")), "p_type", "left_semi").agg(F.count("*").alias("n")))
add("join_inner", "SELECT s_nationkey, CAST(count(*) AS BIGINT) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1", lambda s, d: line(s, d).join(supp(s, d), c("l_suppkey") == c("s_suppkey")).groupBy("s_nationkey").agg(F.count("*").alias("n")))
for _hint in ("broadcast", "shuffle_hash", "merge"):
    add(f"join_inner_{_hint}", "SELECT s_nationkey, CAST(count(*) AS BIGINT) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1", lambda s, d, h=_hint: line(s, d).join(supp(s, d).hint(h), c("l_suppkey") == c("s_suppkey")).groupBy("s_nationkey").agg(F.count("*").alias("n")))
for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    add(f"join_{_how}", f"SELECT coalesce(c_custkey, -1) AS c_custkey, CAST(count(o_orderkey) AS BIGINT) AS n FROM customer {_sql} JOIN orders ON c_custkey = o_custkey AND o_totalprice > 300000 GROUP BY 1", lambda s, d, h=_how: cust(s, d).join(orders(s, d), (c("c_custkey") == c("o_custkey")) & (c("o_totalprice") > 300000), h).groupBy(F.coalesce("c_custkey", F.lit(-1)).alias("c_custkey")).agg(F.count("o_orderkey").alias("n")))
for _how, _not in (("semi", ""), ("anti", "NOT ")):
    add(f"join_{_how}", f"SELECT c_custkey FROM customer WHERE {_not}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)", lambda s, d, h=_how: cust(s, d).join(orders(s, d).where("o_totalprice > 300000"), c("c_custkey") == c("o_custkey"), f"left_{h}").select("c_custkey"))
add("join_cross", "SELECT a.n_nationkey AS a, b.r_regionkey AS b FROM nation a CROSS JOIN region b", lambda s, d: load(s, d, "nation").select(c("n_nationkey").alias("a")).crossJoin(load(s, d, "region").select(c("r_regionkey").alias("b"))))


def range_join(points: DataFrame, at: str, ranges: DataFrame, lo: str, hi: str, width: float) -> DataFrame:
    """Points in [lo, hi): both sides meet on the number of a bin, so it is an equi-join and not a nested loop."""
    bins = F.explode(F.sequence(F.floor(c(lo) / width).cast("long"), F.floor(c(hi) / width).cast("long")))
    left, right = points.withColumn("__b", F.floor(c(at) / width).cast("long")), ranges.withColumn("__b", bins)
    return left.join(right, "__b").where((c(at) >= c(lo)) & (c(at) < c(hi))).drop("__b")


add("join_range", "SELECT n_nationkey, CAST(count(*) AS BIGINT) AS n FROM orders JOIN (SELECT n_nationkey, n_nationkey * 10000.0 AS lo, n_nationkey * 10000.0 + 15000.0 AS hi FROM nation) ON o_totalprice >= lo AND o_totalprice < hi GROUP BY 1", lambda s, d: range_join(orders(s, d), "o_totalprice", load(s, d, "nation").selectExpr("n_nationkey", "n_nationkey * 10000.0D as lo", "n_nationkey * 10000.0D + 15000.0D as hi"), "lo", "hi", 15000.0).groupBy("n_nationkey").agg(F.count("*").alias("n")))


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: list[str], salts: int = 1) -> DataFrame:
    """Each left row with the last right row at or before it, by a running last value over both; the keys are `by`."""
    both = left.withColumn("__side", F.lit(1)).unionByName(right.withColumn("__side", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    tagged = F.when(c("__side") == 0, F.struct(*value))
    return both.withColumn("__last", F.last(tagged, ignorenulls=True).over(w)).where("__side = 1").select(*left.columns, *[c(f"__last.{v}").alias(v) for v in value])


add("join_asof", "SELECT event_id, coalesce(o_orderdate_max, -1) AS last_order FROM (SELECT event_id, (SELECT CAST(epoch(max(o_orderdate)) AS BIGINT) FROM orders WHERE o_custkey = user_id AND o_orderdate <= ts + INTERVAL 0 DAY) AS o_orderdate_max FROM events)", lambda s, d: asof_join(ev(s, d).select("event_id", c("user_id").alias("k"), c("ts").alias("at")), orders(s, d).select(c("o_custkey").alias("k"), c("o_orderdate").alias("at"), c("o_orderdate").alias("d")), "k", "at", ["d"]).select("event_id", F.coalesce(F.unix_seconds(c("d").cast("timestamp")), F.lit(-1)).alias("last_order")))
add("agg_distinct", "SELECT CAST(count(DISTINCT l_suppkey) AS BIGINT) AS s, CAST(count(DISTINCT l_partkey) AS BIGINT) AS p FROM lineitem", lambda s, d: line(s, d).agg(F.countDistinct("l_suppkey").alias("s"), F.countDistinct("l_partkey").alias("p")))
query("agg_approx_distinct")(lambda s, d: line(s, d).agg(F.approx_count_distinct("l_partkey", 0.01).alias("p")))
add("agg_filter", "SELECT l_returnflag, CAST(count(*) FILTER (WHERE l_discount > 0.05) AS BIGINT) AS n, sum(l_quantity) FILTER (WHERE l_tax > 0.02) AS q FROM lineitem GROUP BY 1", lambda s, d: line(s, d).groupBy("l_returnflag").agg(F.count(F.when(c("l_discount") > 0.05, 1)).alias("n"), F.sum(F.when(c("l_tax") > 0.02, c("l_quantity"))).alias("q")))
for _kind in ("rollup", "cube"):
    add(f"agg_{_kind}", f"SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY {_kind}(l_returnflag, l_linestatus)", lambda s, d, k=_kind: getattr(line(s, d), k)("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q"), F.count("*").alias("n")))
add("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))", lambda s, d: line(s, d).groupingSets([[c("l_returnflag")], [c("l_linestatus")]], c("l_returnflag"), c("l_linestatus")).agg(F.sum("l_quantity").alias("q")))
add("stats_corr", f"SELECT {sig_sql('10 + corr(l_quantity, l_extendedprice)')} AS corr, {sig_sql('covar_pop(l_extendedprice, l_discount)')} AS cov, {sig_sql('var_pop(l_quantity)')} AS var, {sig_sql('stddev_samp(l_tax)')} AS sd FROM lineitem", lambda s, d: line(s, d).agg(sig(10 + F.corr("l_quantity", "l_extendedprice")).alias("corr"), sig(F.covar_pop("l_extendedprice", "l_discount")).alias("cov"), sig(F.var_pop("l_quantity")).alias("var"), sig(F.stddev_samp("l_tax")).alias("sd")))
add("window_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)", lambda s, d: orders(s, d).select("o_orderkey", F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")).cast("long").alias("rn"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).cast("long").alias("rk"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).cast("long").alias("dr")))
add("window_running", "SELECT o_orderkey, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS s FROM orders", lambda s, d: orders(s, d).select("o_orderkey", F.sum(F.round(c("o_totalprice") * 100).cast("long")).over(Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, 0)).alias("s")))
add("window_lag", "SELECT o_orderkey, coalesce(lag(o_orderkey) OVER w, -1) AS prev, coalesce(lead(o_orderkey) OVER w, -1) AS next FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)", lambda s, d: orders(s, d).select("o_orderkey", F.lag("o_orderkey", 1, -1).over(w := Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias("prev"), F.lead("o_orderkey", 1, -1).over(w).alias("next")))
add("window_range", "SELECT p_partkey, CAST(count(*) OVER (PARTITION BY p_type ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS n FROM part", lambda s, d: part(s, d).select("p_partkey", F.count("*").over(Window.partitionBy("p_type").orderBy("p_size").rangeBetween(-2, 2)).alias("n")))
add("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25", lambda s, d: orders(s, d).select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25))
_a, _b = (lambda s, d: orders(s, d).where("o_totalprice > 200000").select("o_custkey")), (lambda s, d: orders(s, d).where("o_orderpriority like '1%'").select("o_custkey"))
_sa, _sb = "SELECT o_custkey FROM orders WHERE o_totalprice > 200000", "SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1%'"
add("set_union_all", f"{_sa} UNION ALL {_sb}", lambda s, d: _a(s, d).unionAll(_b(s, d)))
add("set_intersect_all", f"{_sa} INTERSECT ALL {_sb}", lambda s, d: _a(s, d).intersectAll(_b(s, d)))
add("set_except_all", f"{_sa} EXCEPT ALL {_sb}", lambda s, d: _a(s, d).exceptAll(_b(s, d)))
add("fn_string", "SELECT p_partkey, upper(p_name) AS u, CAST(length(p_name) AS BIGINT) AS n, replace(p_brand, '#', '-') AS b, substring(p_type, 1, 3) AS t FROM part", lambda s, d: part(s, d).select("p_partkey", F.upper("p_name").alias("u"), F.length("p_name").cast("long").alias("n"), F.regexp_replace("p_brand", "#", "-").alias("b"), F.substring("p_type", 1, 3).alias("t")))
add("fn_date", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(month(o_orderdate) AS BIGINT) AS m, CAST(epoch(date_trunc('month', o_orderdate)) AS BIGINT) AS t FROM orders", lambda s, d: orders(s, d).select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), F.unix_seconds(F.date_trunc("month", c("o_orderdate").cast("timestamp"))).alias("t")))
add("fn_math", f"SELECT p_partkey, {sig_sql('sqrt(p_retailprice)')} AS r, {sig_sql('ln(p_retailprice)')} AS l, {sig_sql('power(p_size, 1.5)')} AS p FROM part", lambda s, d: part(s, d).select("p_partkey", sig(F.sqrt("p_retailprice")).alias("r"), sig(F.log("p_retailprice")).alias("l"), sig(F.pow("p_size", F.lit(1.5))).alias("p")))
add("fn_array", f"SELECT vec_id, {sig_sql('list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x))')} AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS pos FROM embeddings", lambda s, d: load(s, d, "embeddings").select("vec_id", sig(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos")))
add("fn_map", "SELECT p_partkey, p_brand AS v, CAST(2 AS BIGINT) AS n FROM part", lambda s, d: part(s, d).withColumn("m", F.create_map(F.lit("brand"), c("p_brand"), F.lit("type"), c("p_type"))).select("p_partkey", F.element_at("m", "brand").alias("v"), F.size(F.map_keys("m")).cast("long").alias("n")))
add("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events", lambda s, d: ev(s, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))


def index_codes(df: DataFrame, col: str) -> DataFrame:
    """(category, code) in order of frequency, ties by name; as many rows as categories."""
    n = df.groupBy(col).agg(F.count("*").alias("n"))
    return n.select(col, (F.row_number().over(Window.partitionBy(F.lit(1)).orderBy(F.desc("n"), col)) - 1).cast("long").alias("code"))


add("encode_index", "SELECT p_type, row_number() OVER (ORDER BY count(*) DESC, p_type) - 1 AS code FROM part GROUP BY 1", lambda s, d: index_codes(part(s, d), "p_type"))
add("encode_onehot", "SELECT p_partkey, CAST(p_type = (SELECT min(p_type) FROM part) AS INTEGER) AS h FROM part", lambda s, d: part(s, d).join(F.broadcast(part(s, d).agg(F.min("p_type").alias("m"))), F.lit(True)).select("p_partkey", (c("p_type") == c("m")).cast("int").alias("h")))
add("encode_bucket", "SELECT p_partkey, CAST(CASE WHEN p_size <= 10 THEN 0 WHEN p_size <= 25 THEN 1 WHEN p_size <= 40 THEN 2 ELSE 3 END AS INTEGER) AS b FROM part", lambda s, d: part(s, d).select("p_partkey", F.when(c("p_size") <= 10, 0).when(c("p_size") <= 25, 1).when(c("p_size") <= 40, 2).otherwise(3).alias("b")))
add("encode_interaction", f"SELECT l_orderkey, l_linenumber, l_partkey, l_discount * l_tax AS dt, l_tax * l_tax AS tt FROM lineitem", lambda s, d: line(s, d).select("l_orderkey", "l_linenumber", "l_partkey", (c("l_discount") * c("l_tax")).alias("dt"), (c("l_tax") * c("l_tax")).alias("tt")))
add("encode_standardise", f"SELECT p_partkey, {sig_sql('100 + (p_retailprice - m) / sd')} AS z FROM part, (SELECT avg(p_retailprice) AS m, stddev_pop(p_retailprice) AS sd FROM part)", lambda s, d: part(s, d).crossJoin(F.broadcast(part(s, d).agg(F.avg("p_retailprice").alias("m"), F.stddev_pop("p_retailprice").alias("sd")))).select("p_partkey", sig(100 + (c("p_retailprice") - c("m")) / c("sd")).alias("z")))
add("sample_quarter", "SELECT CAST(count(*) AS BIGINT) AS n FROM lineitem WHERE l_orderkey % 4 = 0", lambda s, d: line(s, d).where("l_orderkey % 4 = 0").agg(F.count("*").alias("n")))
add("split_kfold", "SELECT CAST(l_orderkey % 5 AS BIGINT) AS fold, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY 1", lambda s, d: line(s, d).groupBy((c("l_orderkey") % 5).alias("fold")).agg(F.count("*").alias("n")))
add("text_features", "SELECT doc_id, n_chars, CAST(len(string_split(text, ' ')) AS BIGINT) AS words FROM documents JOIN labels USING (doc_id)", lambda s, d: load(s, d, "documents").join(load(s, d, "labels"), "doc_id").select("doc_id", "n_chars", F.size(F.split("text", " ")).cast("long").alias("words")))
add("udf_predict", f"SELECT l_orderkey, l_linenumber, l_partkey, CAST(20 AS DOUBLE) + CAST(3 AS DOUBLE) * l_discount + CAST(-2 AS DOUBLE) * l_tax AS p FROM lineitem", lambda s, d: line(s, d).select("l_orderkey", "l_linenumber", "l_partkey", predictor([20.0, 3.0, -2.0])("l_discount", "l_tax").alias("p")))
add("udaf_gram", " UNION ALL ".join(f"SELECT p_type AS g, CAST({i} AS BIGINT) AS i, CAST({j} AS BIGINT) AS j, {sig_sql(f'sum({a} * {b})')} AS v FROM part GROUP BY 1" for i, a in enumerate(("p_size", "p_retailprice")) for j, b in enumerate(("p_size", "p_retailprice"))), lambda s, d: (g := gram_by(part(s, d), "p_type", ["p_size", "p_retailprice"])).select("g", "i", "j", sig(g.v).alias("v")))


def pairs(s: SparkSession, d: str) -> DataFrame:
    s.udtf.register("explode_pairs", ExplodePairs)
    return s.sql("SELECT n_nationkey AS k, i, j, value FROM {t}, LATERAL explode_pairs(array(n_nationkey, n_regionkey, 2))", t=load(s, d, "nation"))


add("udtf_pairs", "WITH v AS (SELECT n_nationkey AS k, [n_nationkey, n_regionkey, 2] AS x FROM nation), r AS (SELECT CAST(range AS INTEGER) AS i FROM range(3)) SELECT k, a.i AS i, b.i AS j, CAST(x[a.i + 1] * x[b.i + 1] AS DOUBLE) AS value FROM v, r a, r b WHERE a.i <= b.i", pairs)


def sql_surface(s: SparkSession, d: str) -> DataFrame:
    return s.sql("SELECT l_returnflag, sum(l_quantity) AS q FROM {t} WHERE l_discount >= :d GROUP BY 1", args={"d": 0.05}, t=line(s, d))


add("sql_parameters", "SELECT l_returnflag, sum(l_quantity) AS q FROM lineitem WHERE l_discount >= 0.05 GROUP BY 1", sql_surface)
