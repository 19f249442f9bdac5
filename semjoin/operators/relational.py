"""Relational operators that surround semantic joins, each as a query with an SQL twin."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semjoin.sources.tables import TABLES, load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key], ORACLES[key] = f, sql
        return f

    return add


def _t(*names: str):
    """A query from a function of tables."""
    return lambda f: lambda spark, sf_dir: f(*[load(spark, sf_dir, n) for n in names])


def _n() -> Column:
    return F.count(F.lit(1))


def _by() -> Window:
    return Window.partitionBy("user_id").orderBy("event_id")


_KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}
for _name in TABLES:
    query(f"SELECT count(*) AS n, CAST(sum({_KEYS[_name]} % 1009) AS BIGINT) AS s FROM {_name}", f"scan_{_name}")(_t(_name)(lambda x, k=_KEYS[_name]: x.agg(_n().alias("n"), F.sum(F.col(k) % 1009).alias("s"))))

# Filters.
query("SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#7', 'Brand#20')", "filter_between_in")(_t("part")(lambda p: p.where(F.col("p_size").between(5, 20) & F.col("p_brand").isin("Brand#7", "Brand#20")).select("p_partkey")))
query("SELECT p_partkey FROM part WHERE p_name LIKE '%bolt%' OR p_name ILIKE 'RED%'", "filter_like")(_t("part")(lambda p: p.where(F.col("p_name").like("%bolt%") | F.col("p_name").ilike("RED%")).select("p_partkey")))
query("SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}')", "filter_regex")(_t("documents")(lambda d: d.where(F.col("text").rlike("[0-9]{3}")).select("doc_id")))
query("SELECT doc_id FROM documents WHERE nullif(lang, 'en') IS NOT DISTINCT FROM NULL", "filter_null_safe")(_t("documents")(lambda d: d.where(F.nullif("lang", F.lit("en")).eqNullSafe(F.lit(None))).select("doc_id")))
query("SELECT event_id FROM events WHERE CAST(ts AS DATE) = DATE '2024-01-10' AND value > 10", "filter_date")(_t("events")(lambda e: e.where((F.to_date("ts") == F.lit("2024-01-10").cast("date")) & (F.col("value") > 10)).select("event_id")))

# Joins.
_CO = "FROM customer c {} JOIN orders o ON c.c_custkey = o.o_custkey"


#: Rows of the smaller side that may be broadcast: two of its longs and their index take some 50 bytes a row on the driver.
MAX_BROADCAST = 2_000_000


def broadcast_smaller(a: DataFrame, b: DataFrame, most: int = MAX_BROADCAST) -> tuple[DataFrame, DataFrame]:
    """Both sides, the smaller one, by count, with a broadcast hint; beyond `most` rows there is none, for a shuffle join."""
    n, m = a.count(), b.count()
    if min(n, m) > most:
        return a, b
    return (F.broadcast(a), b) if n <= m else (a, F.broadcast(b))


def _co(how: str, hint: str | None = None):
    def run(c: DataFrame, o: DataFrame) -> DataFrame:
        o = o.select("o_orderkey", "o_custkey")
        c = c.select("c_custkey")
        if hint == "broadcast":
            c, o = broadcast_smaller(c, o)
        elif hint:
            o = o.hint(hint)
        out = c.join(o, c["c_custkey"] == o["o_custkey"], how)
        return out if how in ("left_semi", "left_anti") else out.select("c_custkey", "o_orderkey")

    return _t("customer", "orders")(run)


for _how, _sql in (("inner", "INNER"), ("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    query(f"SELECT c_custkey, o_orderkey {_CO.format(_sql)}", f"join_{_how}")(_co(_how))
query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)", "join_semi")(_co("left_semi"))
query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)", "join_anti")(_co("left_anti"))
for _hint in ("broadcast", "merge", "shuffle_hash"):
    query(f"SELECT c_custkey, o_orderkey {_CO.format('INNER')}", f"join_hint_{_hint}")(_co("inner", _hint))
query("SELECT r_name, n_name FROM region, nation", "join_cross")(_t("region", "nation")(lambda r, x: r.select("r_name").crossJoin(x.select("n_name"))))
query("SELECT a.s_suppkey AS x, b.s_suppkey AS y FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey", "join_self")(
    _t("supplier")(lambda s: s.select(F.col("s_suppkey").alias("x"), F.col("s_nationkey").alias("n")).join(s.select(F.col("s_suppkey").alias("y"), F.col("s_nationkey").alias("n")), "n").where("x < y").select("x", "y")))
query("SELECT a.n_nationkey AS x, b.n_nationkey AS y FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey", "join_theta")(_t("nation")(lambda x: x.select(F.col("n_nationkey").alias("x"), F.col("n_regionkey").alias("rx")).join(x.select(F.col("n_nationkey").alias("y"), F.col("n_regionkey").alias("ry")), F.col("rx") < F.col("ry")).select("x", "y")))
query("SELECT a.doc_id AS x, b.lang AS lang FROM documents a JOIN (SELECT DISTINCT nullif(lang, 'en') AS lang FROM documents) b ON nullif(a.lang, 'en') IS NOT DISTINCT FROM b.lang", "join_null_safe")(
    _t("documents")(lambda d: d.select(F.col("doc_id").alias("x"), F.nullif("lang", F.lit("en")).alias("l")).join(d.select(F.nullif("lang", F.lit("en")).alias("lang")).distinct(), F.col("l").eqNullSafe(F.col("lang"))).select("x", "lang")))
query("SELECT b.lo AS lo, count(*) AS n FROM part p JOIN (SELECT range AS lo FROM range(0, 50, 10)) b ON p.p_size >= b.lo AND p.p_size < b.lo + 10 GROUP BY 1", "join_range")(
    _t("part")(lambda p: p.join(F.broadcast(p.sparkSession.range(0, 50, 10).withColumnRenamed("id", "lo")), (F.col("p_size") >= F.col("lo")) & (F.col("p_size") < F.col("lo") + 10)).groupBy("lo").agg(_n().alias("n"))))


@query("SELECT e.event_id AS event_id, max(s.event_id) AS before FROM (SELECT * FROM events WHERE event_type = 'error') e JOIN (SELECT * FROM events WHERE event_type = 'signup') s ON s.user_id = e.user_id AND s.event_id < e.event_id GROUP BY e.event_id")
def join_asof(spark, sf_dir):
    """The last signup of the same user before each error: one shuffle by user, no pairs."""
    e = load(spark, sf_dir, "events").where("event_type in ('error', 'signup')")
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("before", last).where("event_type = 'error' and before is not null").select("event_id", "before")


@query("SELECT r_name, count(*) AS n, CAST(sum(l_quantity) AS DOUBLE) AS q FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def join_multiway(spark, sf_dir):
    r, x, c, o, li = (load(spark, sf_dir, t) for t in ("region", "nation", "customer", "orders", "lineitem"))
    out = li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, o["o_custkey"] == c["c_custkey"]).join(x, c["c_nationkey"] == x["n_nationkey"]).join(r, x["n_regionkey"] == r["r_regionkey"])
    return out.groupBy("r_name").agg(_n().alias("n"), F.sum("l_quantity").cast("double").alias("q"))


# Aggregation.
query("SELECT p_brand, count(*) AS n, min(p_size) AS lo, max(p_size) AS hi, round(avg(p_size), 4) AS mean FROM part GROUP BY 1 HAVING count(*) > 5", "agg_group_having")(_t("part")(lambda p: p.groupBy("p_brand").agg(_n().alias("n"), F.min("p_size").alias("lo"), F.max("p_size").alias("hi"), F.round(F.avg("p_size"), 4).alias("mean")).where("n > 5")))
query("SELECT event_type, count(DISTINCT user_id) AS u FROM events GROUP BY 1", "agg_distinct")(_t("events")(lambda e: e.groupBy("event_type").agg(F.countDistinct("user_id").alias("u"))))
for _kind in ("rollup", "cube"):
    query(f"SELECT lang, source, count(*) AS n FROM documents GROUP BY {_kind.upper()}(lang, source)", f"agg_{_kind}")(_t("documents")(lambda d, k=_kind: getattr(d, k)("lang", "source").agg(_n().alias("n"))))
query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", "agg_grouping_sets")(_t("documents")(lambda d: d.groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source").agg(_n().alias("n"))))
query("SELECT user_id % 5 AS g, count(CASE WHEN event_type = 'error' THEN 1 END) AS error, count(CASE WHEN event_type = 'signup' THEN 1 END) AS signup FROM events GROUP BY 1", "agg_pivot")(_t("events")(lambda e: e.groupBy((F.col("user_id") % 5).alias("g")).pivot("event_type", ["error", "signup"]).agg(_n()).fillna(0)))
query("SELECT lang, arg_max(doc_id, n_chars * 1000000 + doc_id) AS longest FROM documents GROUP BY 1", "agg_max_by")(_t("documents")(lambda d: d.groupBy("lang").agg(F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"))))
query("SELECT lang, count(*) AS n, string_agg(CAST(doc_id AS VARCHAR), ',' ORDER BY doc_id) AS ids FROM documents GROUP BY 1", "agg_collect")(_t("documents")(
    lambda d: d.groupBy("lang").agg(_n().alias("n"), F.concat_ws(",", F.transform(F.array_sort(F.collect_list("doc_id")), lambda x: x.cast("string"))).alias("ids"))))
query("SELECT round(corr(p_size, p_retailprice), 6) AS r, round(stddev_samp(p_size), 6) AS s FROM part", "agg_stats")(_t("part")(lambda p: p.agg(F.round(F.corr("p_size", "p_retailprice"), 6).alias("r"), F.round(F.stddev("p_size"), 6).alias("s"))))
query("SELECT round(quantile_cont(p_size, 0.5), 4) AS mid, round(quantile_cont(p_size, 0.9), 4) AS high FROM part", "agg_percentile")(_t("part")(lambda p: p.agg(F.round(F.percentile("p_size", 0.5), 4).alias("mid"), F.round(F.percentile("p_size", 0.9), 4).alias("high"))))

# Windows.
def _win(name: str, sql: str, f) -> None:
    query(f"SELECT event_id, {sql} AS x FROM events", f"win_{name}")(_t("events")(lambda e: e.select("event_id", f().alias("x"))))


_W = "OVER (PARTITION BY user_id ORDER BY event_id{})"
_win("row_number", "row_number() " + _W.format(""), lambda: F.row_number().over(_by()))
_win("rank", "rank() OVER (PARTITION BY event_type ORDER BY user_id)", lambda: F.rank().over(Window.partitionBy("event_type").orderBy("user_id")))
_win("dense_rank", "dense_rank() OVER (PARTITION BY event_type ORDER BY user_id)", lambda: F.dense_rank().over(Window.partitionBy("event_type").orderBy("user_id")))
_win("ntile", "ntile(4) " + _W.format(""), lambda: F.ntile(4).over(_by()))
_win("percent_rank", "round(percent_rank() " + _W.format("") + ", 6)", lambda: F.round(F.percent_rank().over(_by()), 6))
_win("cume_dist", "round(cume_dist() " + _W.format("") + ", 6)", lambda: F.round(F.cume_dist().over(_by()), 6))
_win("lag", "lag(event_id, 1) " + _W.format(""), lambda: F.lag("event_id", 1).over(_by()))
_win("lead", "lead(event_id, 2, -1) " + _W.format(""), lambda: F.lead("event_id", 2, -1).over(_by()))
_win("first", "first_value(event_id) " + _W.format(""), lambda: F.first("event_id").over(_by()))
_win("nth", "nth_value(event_id, 2) " + _W.format(""), lambda: F.nth_value("event_id", 2).over(_by()))
_win("frame_rows", "CAST(sum(event_id) " + _W.format(" ROWS BETWEEN 2 PRECEDING AND CURRENT ROW") + " AS BIGINT)", lambda: F.sum("event_id").over(_by().rowsBetween(-2, 0)))
_win("frame_range", "count(*) " + _W.format(" RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING"), lambda: F.count(F.lit(1)).over(_by().rangeBetween(-100, 100)))
_win("running", "CAST(sum(event_id) " + _W.format(" ROWS UNBOUNDED PRECEDING") + " AS BIGINT)", lambda: F.sum("event_id").over(_by().rowsBetween(Window.unboundedPreceding, 0)))

# Sets, order, top k.
for _op, _m in (("union", "union"), ("intersect", "intersect"), ("except", "subtract"), ("intersect_all", "intersectAll"), ("except_all", "exceptAll"), ("union_all", "unionAll")):
    query(f"SELECT user_id FROM events WHERE event_type = 'error' {_op.upper().replace('_', ' ')} SELECT user_id FROM events WHERE event_type = 'signup'", f"set_{_op}")(
        _t("events")(lambda e, m=_m, d=_op == "union": (x := getattr(e.where("event_type = 'error'").select("user_id"), m)(e.where("event_type = 'signup'").select("user_id"))) if not d else e.where("event_type in ('error', 'signup')").select("user_id").distinct()))
query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20", "topk_global")(_t("orders")(lambda o: o.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")))
query("SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) x WHERE r <= 3", "topk_per_group")(_t("orders")(lambda o: o.withColumn("r", F.row_number().over(Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 3").select("o_orderpriority", "o_orderkey")))
query("SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 5", "topk_offset")(_t("orders")(lambda o: o.orderBy("o_orderkey").offset(5).limit(10).select("o_orderkey")))

# Functions.
query("SELECT doc_id, upper(lang) AS u, substr(source, 4) AS s, length(trim(text)) AS n, replace(source, 'src', '#') AS r, lpad(lang, 4, '.') AS p, md5(text) AS h, strpos(text, 'th') AS i FROM documents", "fn_string")(_t("documents")(
    lambda d: d.select("doc_id", F.upper("lang").alias("u"), F.substring("source", 4, 100).alias("s"), F.length(F.trim("text")).alias("n"), F.replace("source", F.lit("src"), F.lit("#")).alias("r"), F.lpad("lang", 4, ".").alias("p"), F.md5("text").alias("h"), F.instr("text", "th").alias("i"))))
query("SELECT event_id, CAST(date_trunc('month', ts) AS DATE) AS m, CAST(extract(DAY FROM ts) AS INT) AS d, CAST(extract(HOUR FROM ts) AS INT) AS h, strftime(ts, '%Y-%m-%d') AS s, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS n FROM events", "fn_date")(_t("events")(
    lambda e: e.select("event_id", F.to_date(F.date_trunc("month", "ts")).alias("m"), F.dayofmonth("ts").alias("d"), F.hour("ts").alias("h"), F.date_format("ts", "yyyy-MM-dd").alias("s"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long").alias("n"))))
query("SELECT p_partkey, p_size // 7 AS q, p_size % 7 AS m, greatest(p_size, 20) AS g, round(sqrt(p_size), 6) AS r, CAST(ceil(p_size / 4.0) AS BIGINT) AS c FROM part", "fn_math")(_t("part")(
    lambda p: p.select("p_partkey", F.expr("int(p_size div 7)").alias("q"), (F.col("p_size") % 7).alias("m"), F.greatest("p_size", F.lit(20)).alias("g"), F.round(F.sqrt("p_size"), 6).alias("r"), F.ceil(F.col("p_size") / 4.0).alias("c"))))
query("SELECT p_partkey, array_to_string(list_sort(string_split(p_name, ' ')), '|') AS w, len(string_split(p_name, ' ')) AS n, list_contains(string_split(p_name, ' '), 'bolt') AS b FROM part", "fn_array")(_t("part")(
    lambda p: p.select("p_partkey", F.array_join(F.array_sort(F.split("p_name", " ")), "|").alias("w"), F.size(F.split("p_name", " ")).cast("long").alias("n"), F.array_contains(F.split("p_name", " "), "bolt").alias("b"))))
query("SELECT event_id, CASE event_type WHEN 'error' THEN 'bad' WHEN 'signup' THEN 'new' END AS m, 2 AS n FROM events", "fn_map")(
    _t("events")(lambda e: e.select("event_id", F.element_at((m := F.create_map(F.lit("error"), F.lit("bad"), F.lit("signup"), F.lit("new"))), F.col("event_type")).alias("m"), F.size(F.map_keys(m)).alias("n"))))
query("SELECT word, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS word FROM part) x GROUP BY 1", "fn_explode")(_t("part")(lambda p: p.select(F.explode(F.split("p_name", " ")).alias("word")).groupBy("word").agg(_n().alias("n"))))
query("SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, regexp_extract(url, '^https?://([^/]+)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages", "fn_html")(
    _t("pages")(lambda p: p.select("page_id", F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("lang"), F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n"))))
query("SELECT event_id, json_extract_string(to_json({'t': event_type, 'u': user_id}), '$.t') AS t FROM events", "fn_json")(_t("events")(
    lambda e: e.select("event_id", F.get_json_object(F.to_json(F.struct(F.col("event_type").alias("t"), F.col("user_id").alias("u"))), "$.t").alias("t"))))
query("SELECT doc_id FROM documents WHERE ('0x' || substr(md5(concat('7:', CAST(doc_id AS VARCHAR))), 1, 8))::UBIGINT % 100 < 10", "sample_bernoulli")(_t("documents")(lambda d: d.where(F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("7"), F.col("doc_id").cast("string"))), 1, 8), 16, 10).cast("long") % 100 < 10).select("doc_id")))
query("SELECT doc_id FROM documents ORDER BY md5(concat('7:', CAST(doc_id AS VARCHAR))), doc_id LIMIT 25", "sample_bottom_n")(_t("documents")(lambda d: d.orderBy(F.md5(F.concat_ws(":", F.lit("7"), F.col("doc_id").cast("string"))), "doc_id").limit(25).select("doc_id")))
query("SELECT lang, doc_id FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY md5(concat('7:', CAST(doc_id AS VARCHAR))), doc_id) AS r FROM documents) x WHERE r <= 5", "sample_stratified")(_t("documents")(lambda d: d.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.md5(F.concat_ws(":", F.lit("7"), F.col("doc_id").cast("string"))), "doc_id"))).where("r <= 5").select("lang", "doc_id")))
