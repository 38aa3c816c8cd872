"""Relational and scalar surface: joins, aggregates, windows, set operations, functions, over the given tables."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import urls
from ..sources import pages as page_io
from .common import table

CALLS: dict = {}
ORACLES: dict[str, str] = {}


def case(sql: str | None):
    """Register a query under its function's name, with its SQL."""

    def keep(f):
        CALLS[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


@case("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity > 45")
def r_scan_parquet(spark, sf):
    return table(spark, sf, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_partkey", "l_quantity")


@case("SELECT conv_id, turn, role, sha256(text) AS digest FROM conversations")
def r_scan_json_roundtrip(spark, sf):
    path = page_io.shared_path(spark, "json")
    df = table(spark, sf, "conversations")
    df.write.json(path)
    return spark.read.schema(df.schema).json(path).select("conv_id", "turn", "role", F.sha2("text", 256).alias("digest"))


@case("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def r_scan_csv_roundtrip(spark, sf):
    path = page_io.shared_path(spark, "csv")
    df = table(spark, sf, "nation").select("n_nationkey", "n_name", "n_regionkey")
    df.write.option("header", "true").csv(path)
    return spark.read.schema(df.schema).option("header", "true").csv(path)


@case("SELECT l_orderkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def r_project(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@case("SELECT doc_id FROM documents WHERE lang IN ('fr', 'de') AND n_chars BETWEEN 500 AND 2000 AND regexp_matches(text, '^[A-Z]') AND source IS NOT NULL")
def r_filter(spark, sf):
    d = table(spark, sf, "documents")
    return d.where(F.col("lang").isin("fr", "de") & F.col("n_chars").between(500, 2000) & F.col("text").rlike("^[A-Z]") & F.col("source").isNotNull()).select("doc_id")


@case("SELECT doc_id, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 3000 THEN 'medium' ELSE 'long' END AS size FROM documents")
def r_case(spark, sf):
    size = F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 3000, "medium").otherwise("long")
    return table(spark, sf, "documents").select("doc_id", size.alias("size"))


def _joined(how, sql_how):
    def call(spark, sf):
        c = table(spark, sf, "customer").select("c_custkey", "c_nationkey").where("c_custkey % 3 <> 0")
        o = table(spark, sf, "orders").select("o_orderkey", "o_custkey").where("o_orderkey % 5 = 0")
        return c.join(o, c.c_custkey == o.o_custkey, how).select("c_custkey", "o_orderkey")

    sql = f"SELECT c_custkey, o_orderkey FROM (SELECT * FROM customer WHERE c_custkey % 3 <> 0) {sql_how} JOIN (SELECT * FROM orders WHERE o_orderkey % 5 = 0) ON c_custkey = o_custkey"
    CALLS[f"r_join_{how}"], ORACLES[f"r_join_{how}"] = call, sql


def _joined_whole(how, sql_how):
    def call(spark, sf):
        c, o = table(spark, sf, "customer").select("c_custkey"), table(spark, sf, "orders").select("o_orderkey", "o_custkey")
        return c.join(o, c.c_custkey == o.o_custkey, how).select("c_custkey", "o_orderkey")

    CALLS[f"r_join_{how}_all"], ORACLES[f"r_join_{how}_all"] = call, f"SELECT c_custkey, o_orderkey FROM customer {sql_how} JOIN orders ON c_custkey = o_custkey"


for _how, _sql in (("inner", ""), ("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    _joined(_how, _sql)
    _joined_whole(_how, _sql)


@case("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def r_join_semi(spark, sf):
    o = table(spark, sf, "orders").select("o_custkey")
    return table(spark, sf, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@case("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def r_join_anti(spark, sf):
    o = table(spark, sf, "orders").select("o_custkey")
    return table(spark, sf, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@case("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def r_join_theta(spark, sf):
    a, b = table(spark, sf, "nation").alias("a"), table(spark, sf, "nation").alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@case("SELECT r_name, n_name FROM region CROSS JOIN nation")
def r_join_cross(spark, sf):
    return table(spark, sf, "region").select("r_name").crossJoin(table(spark, sf, "nation").select("n_name"))


@case("""WITH c AS (SELECT * FROM (VALUES (0, 0, 20), (1, 20, 60), (2, 60, 1000)) t(bin, low, high))
SELECT bin, count(*) AS events FROM events JOIN c ON value >= low AND value < high GROUP BY bin""")
def r_join_range(spark, sf):
    """Each value meets only the cuts of its own bucket of width 20, which the cut table is spread over."""
    cuts = spark.createDataFrame([(0, 0, 20), (1, 20, 60), (2, 60, 1000)], "bin int, low int, high int")
    spread = cuts.withColumn("b", F.explode(F.sequence(F.floor(F.col("low") / 20).cast("int"), F.floor((F.col("high") - 1) / 20).cast("int"))))
    e = table(spark, sf, "events").select("value").withColumn("b", F.floor(F.col("value") / 20).cast("int"))
    return e.join(F.broadcast(spread), "b").where("value >= low AND value < high").groupBy("bin").agg(F.count(F.lit(1)).alias("events"))


@case("""SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase'
AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR""")
def r_join_interval(spark, sf):
    e = table(spark, sf, "events")
    a = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return a.join(b, "user_id").where("tb > ta AND tb <= ta + INTERVAL 6 HOURS").select("a", "b")


@case("""WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), v AS (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2)
SELECT p.event_id, v.event_id AS latest FROM p ASOF LEFT JOIN v ON p.user_id = v.user_id AND p.ts >= v.ts""")
def r_join_asof(spark, sf):
    """The latest view at or before each purchase: both are put in one order and the last view is carried forward."""
    e = table(spark, sf, "events").where("event_type IN ('view', 'purchase')").select("event_id", "user_id", "ts", "event_type")
    views = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("v")).select("user_id", "ts", "v", F.lit(None).cast("long").alias("event_id"))
    rows = views.unionByName(e.where("event_type = 'purchase'").select("user_id", "ts", F.lit(None).cast("long").alias("v"), "event_id"))
    last = F.last("v", ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", F.col("event_id").isNotNull()).rowsBetween(W.unboundedPreceding, 0))
    return rows.withColumn("latest", last).where("event_id IS NOT NULL").select("event_id", "latest")


@case("SELECT doc_id, count(*) AS n_lines FROM (SELECT doc_id, unnest(string_split(text, chr(10))) FROM documents) GROUP BY doc_id")
def r_join_lateral(spark, sf):
    table(spark, sf, "documents").select("doc_id", "text").createOrReplaceTempView("websieve_lateral")
    return spark.sql("SELECT doc_id, count(*) AS n_lines FROM websieve_lateral, LATERAL explode(split(text, '\\n')) AS t(line) GROUP BY doc_id")


@case("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(avg(l_discount), 6) AS disc, count(*) AS n FROM lineitem GROUP BY ALL")
def r_agg_basic(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count(F.lit(1)).alias("n"))


@case("SELECT lang, count(DISTINCT source) AS sources FROM documents GROUP BY lang")
def r_agg_distinct(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.count_distinct("source").alias("sources"))


@case("SELECT lang, count(*) FILTER (n_chars > 1000) AS long FROM documents GROUP BY lang")
def r_agg_filter(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.count_if(F.col("n_chars") > 1000).alias("long"))


@case("SELECT lang, arg_max(doc_id, n_chars * 1000000 - doc_id) AS longest FROM documents GROUP BY lang")
def r_agg_maxby(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.max_by("doc_id", F.col("n_chars") * 1_000_000 - F.col("doc_id")).alias("longest"))


@case("SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
def r_rollup(spark, sf):
    return table(spark, sf, "documents").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@case("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def r_cube(spark, sf):
    return table(spark, sf, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@case("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source))")
def r_grouping_sets(spark, sf):
    d = table(spark, sf, "documents")
    return d.groupingSets([[F.col("lang")], [F.col("source")]], "lang", "source").agg(F.count(F.lit(1)).alias("n"))


@case("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def r_pivot(spark, sf):
    p = table(spark, sf, "documents").groupBy("source").pivot("lang", ["en", "fr"]).count()
    return p.na.fill(0).select("source", "en", "fr")


@case("SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def r_unpivot(spark, sf):
    return table(spark, sf, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value")


@case(None)
def r_approximate(spark, sf):
    d = table(spark, sf, "documents")
    return d.groupBy("lang").agg(F.approx_count_distinct("text").alias("texts"), F.percentile_approx("n_chars", 0.5, 1000).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("text")).alias("hll"))


@case("SELECT doc_id, (rank() OVER w)::INTEGER AS rank, (dense_rank() OVER w)::INTEGER AS dense, (row_number() OVER (PARTITION BY lang ORDER BY n_chars, doc_id))::INTEGER AS nth FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars)")
def r_win_rank(spark, sf):
    w = W.partitionBy("lang").orderBy("n_chars")
    return table(spark, sf, "documents").select("doc_id", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.row_number().over(W.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("nth"))


@case("SELECT doc_id, (ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id))::INTEGER AS quarter FROM documents")
def r_win_ntile(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.ntile(4).over(W.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("quarter"))


@case("SELECT doc_id, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars)")
def r_win_percent(spark, sf):
    w = W.partitionBy("lang").orderBy("n_chars")
    return table(spark, sf, "documents").select("doc_id", F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@case("SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def r_win_lag(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"))


@case("""SELECT event_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last, nth_value(event_id, 2) OVER w AS second
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def r_win_first_last(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, sf, "events").select("event_id", F.first("event_id").over(w).alias("first"), F.last("event_id").over(w).alias("last"), F.nth_value("event_id", 2).over(w).alias("second"))


@case("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS three FROM events")
def r_win_rows(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return table(spark, sf, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("three"))


@case("SELECT doc_id, count(*) OVER (PARTITION BY lang ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM documents")
def r_win_range(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.count(F.lit(1)).over(W.partitionBy("lang").orderBy("n_chars").rangeBetween(-100, 100)).alias("near"))


@case("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 25")
def r_topk(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(25)


@case("SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS nth FROM documents) WHERE nth <= 5")
def r_topk_group(spark, sf):
    nth = F.row_number().over(W.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id"))
    return table(spark, sf, "documents").withColumn("nth", nth).where("nth <= 5").select("lang", "doc_id")


@case("SELECT doc_id FROM documents ORDER BY doc_id LIMIT 20 OFFSET 40")
def r_offset(spark, sf):
    return table(spark, sf, "documents").select("doc_id").orderBy("doc_id").offset(40).limit(20)


@case("SELECT text FROM benchmark UNION ALL SELECT text FROM conversations")
def r_union(spark, sf):
    return table(spark, sf, "benchmark").select("text").unionByName(table(spark, sf, "conversations").select("text"))


def _sets(spark, sf):
    d = table(spark, sf, "documents")
    return d.where("doc_id % 2 = 0").select("lang", "source"), d.where("doc_id % 3 = 0").select("lang", "source")


def _set_sql(op):
    return f"SELECT lang, source FROM documents WHERE doc_id % 2 = 0 {op} SELECT lang, source FROM documents WHERE doc_id % 3 = 0"


@case(_set_sql("INTERSECT"))
def r_intersect(spark, sf):
    a, b = _sets(spark, sf)
    return a.intersect(b)


@case(_set_sql("EXCEPT"))
def r_except(spark, sf):
    a, b = _sets(spark, sf)
    return a.subtract(b)


@case(_set_sql("EXCEPT ALL"))
def r_except_all(spark, sf):
    a, b = _sets(spark, sf)
    return a.exceptAll(b)


@case("SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
def r_sub_scalar(spark, sf):
    d = table(spark, sf, "documents")
    return d.where(F.col("n_chars") > d.select(F.avg("n_chars")).scalar()).select("doc_id")


@case("SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.toxic = 1)")
def r_sub_exists(spark, sf):
    d, l = table(spark, sf, "documents").alias("d"), table(spark, sf, "labels").alias("l")
    return d.where(l.where((F.col("l.doc_id") == F.col("d.doc_id").outer()) & (F.col("l.toxic") == 1)).exists()).select("doc_id")


@case("SELECT doc_id FROM documents WHERE doc_id % 100 = 7")
def r_sample_mod(spark, sf):
    return table(spark, sf, "documents").where(F.pmod("doc_id", F.lit(100)) == 7).select("doc_id")


@case("SELECT d.doc_id, coalesce(l.quality, -1) AS quality FROM documents d LEFT JOIN labels l USING (doc_id)")
def r_nulls(spark, sf):
    return table(spark, sf, "documents").select("doc_id").join(table(spark, sf, "labels"), "doc_id", "left").na.fill({"quality": -1}).select("doc_id", "quality")


@case("SELECT DISTINCT lang, source FROM documents")
def r_drop_duplicates(spark, sf):
    return table(spark, sf, "documents").select("lang", "source").dropDuplicates()


@case("""SELECT doc_id, lower(substr(text, 1, 20)) AS low, translate(substr(text, 1, 20), 'aeiou', 'AEIOU') AS tr, length(text)::INTEGER AS n, strlen(text)::INTEGER AS bytes, reverse(substr(text, 1, 5)) AS rev,
sha1(text) AS sha, instr(text, ' ')::INTEGER AS blank, levenshtein(lang || source, source)::INTEGER AS lev, regexp_extract(text, '([a-z]+) ', 1) AS word, concat_ws('-', lang, source) AS both FROM documents""")
def f_string(spark, sf):
    t, head = F.col("text"), F.substring("text", 1, 20)
    return table(spark, sf, "documents").select(
        "doc_id", F.lower(head).alias("low"), F.translate(head, "aeiou", "AEIOU").alias("tr"), F.length(t).alias("n"), F.octet_length(t).alias("bytes"), F.reverse(F.substring("text", 1, 5)).alias("rev"), F.sha1(t).alias("sha"),
        F.instr(t, " ").alias("blank"), F.levenshtein(F.concat("lang", "source"), F.col("source")).alias("lev"), F.regexp_extract(t, "([a-z]+) ", 1).alias("word"), F.concat_ws("-", "lang", "source").alias("both"))


@case(rf"""WITH u AS (SELECT page_id, url, lower(regexp_extract(url, '{urls.SCHEME}', 1)) AS scheme, lower(regexp_extract(url, '{urls.HOST}', 1)) AS host, regexp_extract(url, '{urls.PATH}', 1) AS path, regexp_extract(url, '{urls.QUERY}', 1) AS query FROM pages)
SELECT page_id, scheme, host, path, query, regexp_replace(host, '^www\.', '') || regexp_replace(path, '/+$', '') || CASE WHEN query <> '' THEN '?' || query ELSE '' END AS canonical FROM u""")
def f_url(spark, sf):
    u = F.col("url")
    return table(spark, sf, "pages").select("page_id", urls.scheme(u).alias("scheme"), urls.host(u).alias("host"), urls.path(u).alias("path"), urls.query(u).alias("query"), urls.canonical(u).alias("canonical"))


@case("""SELECT event_id, round(log10(value + 1), 6) AS lg, round(pow(value, 0.5), 6) AS root, floor(value)::BIGINT AS low, ceil(value)::BIGINT AS high, greatest(value, 50) AS top, (event_id % 7)::BIGINT AS m, (event_id & 6)::BIGINT AS bits FROM events""")
def f_math(spark, sf):
    v = F.col("value")
    return table(spark, sf, "events").select("event_id", F.round(F.log10(v + 1), 6).alias("lg"), F.round(F.pow(v, 0.5), 6).alias("root"), F.floor(v).alias("low"), F.ceil(v).alias("high"), F.greatest(v, F.lit(50.0)).alias("top"), F.pmod("event_id", F.lit(7)).alias("m"), F.col("event_id").bitwiseAND(6).alias("bits"))


@case("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first FROM orders")
def f_date(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("first"))


@case("""WITH w AS (SELECT doc_id, list_filter(string_split(text, ' '), lambda x: x <> '') AS w FROM documents)
SELECT doc_id, len(list_distinct(w))::INTEGER AS kinds, array_to_string(list_slice(w, 1, 3), '|') AS head, list_sum(list_transform(w, lambda x: length(x)))::INTEGER AS chars, len(list_filter(w, lambda x: length(x) > 8)) > 0 AS long FROM w""")
def f_array(spark, sf):
    w = F.filter(F.split("text", " "), lambda x: x != "")
    return table(spark, sf, "documents").select("doc_id", w.alias("w")).select(
        "doc_id", F.size(F.array_distinct("w")).alias("kinds"), F.array_join(F.slice("w", 1, 3), "|").alias("head"), F.aggregate("w", F.lit(0), lambda a, x: a + F.length(x)).alias("chars"), F.exists("w", lambda x: F.length(x) > 8).alias("long"))


@case("SELECT doc_id, 'quality' AS k, quality AS v FROM labels WHERE quality > 0 UNION ALL SELECT doc_id, 'toxic', toxic FROM labels WHERE toxic > 0")
def f_map(spark, sf):
    m = F.map_filter(F.create_map(F.lit("quality"), F.col("quality"), F.lit("toxic"), F.col("toxic")), lambda k, v: v > 0)
    return table(spark, sf, "labels").select("doc_id", F.explode(m).alias("k", "v"))


@case(None)
def f_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "map<string,string>").alias("m")).select("event_id", F.to_json("m").alias("back"), F.size("m").alias("n"))
