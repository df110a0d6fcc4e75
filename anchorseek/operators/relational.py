"""Relational operators around the methods: one small query each over the given tables, with its SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

QUERIES, SQL = {}, {}


def seconds(ts):
    """Whole seconds since 1970 of a time without zone."""
    return F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), F.col(ts) if isinstance(ts, str) else ts)


def rel(sql=None, name=None):
    """Register a query as rel_<its name>; without sql Spark's and DuckDB's answers cannot be the same rows."""

    def add(f):
        key = f"rel_{name or f.__name__.strip('_')}"

        def run(spark, d):
            return f(lambda t: spark.read.parquet(f"{d}/{t}.parquet"))

        QUERIES[key] = run
        if sql:
            SQL[key] = sql
        return f

    return add


def sql_twin(name, sql, duck=None):
    """The same SQL for both engines, over views of the tables it names."""

    def run(spark, d):
        import re

        for t in set(re.findall(r"\b(region|nation|customer|supplier|part|orders|lineitem|events|documents|embeddings|pages|benchmark|labels|conversations)\b", sql)):
            spark.read.parquet(f"{d}/{t}.parquet").createOrReplaceTempView(t)
        return spark.sql(sql)

    QUERIES[f"rel_{name}"] = run
    SQL[f"rel_{name}"] = duck or sql


@rel("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge, l_quantity::INTEGER AS qty FROM lineitem")
def project_expr(t):
    return t("lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")), 6).alias("charge"), F.col("l_quantity").cast("int").alias("qty"))


@rel("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 5 AND 20 AND l_returnflag IN ('A', 'R') AND NOT (l_linestatus = 'F' OR l_discount > 0.05)")
def filter_compound(t):
    c = F.col
    return t("lineitem").where(c("l_quantity").between(5, 20) & c("l_returnflag").isin("A", "R") & ~((c("l_linestatus") == "F") | (c("l_discount") > 0.05))).select("l_orderkey", "l_linenumber", "l_quantity")


@rel("SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_name, '[0-9]$') UNION ALL SELECT doc_id, source FROM documents WHERE contains(text, 'license')")
def filter_like(t):
    a = t("part").where(F.col("p_name").like("%a%") & F.col("p_name").rlike("[0-9]$")).select("p_partkey", "p_name")
    return a.union(t("documents").where(F.col("text").contains("license")).select("doc_id", "source"))


@rel("SELECT d.doc_id, coalesce(l.quality, -1) AS quality, l.toxic IS NULL AS unlabelled, nullif(d.lang, 'en') AS other_lang, (l.toxic IS NOT DISTINCT FROM NULL) AS same FROM documents d LEFT JOIN labels l USING (doc_id)")
def nulls(t):
    j = t("documents").select("doc_id", "lang").join(t("labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.col("toxic").isNull().alias("unlabelled"), F.nullif("lang", F.lit("en")).alias("other_lang"), F.col("toxic").eqNullSafe(F.lit(None)).alias("same"))


@rel("SELECT doc_id, CASE WHEN n_chars < 100 THEN 'short' WHEN n_chars < 2000 THEN 'middle' ELSE 'long' END AS size FROM documents")
def case_when(t):
    return t("documents").select("doc_id", F.when(F.col("n_chars") < 100, "short").when(F.col("n_chars") < 2000, "middle").otherwise("long").alias("size"))


@rel("SELECT r_name, count(*)::BIGINT AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def join_broadcast(t):
    small = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows at any scale
    return t("customer").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@rel("SELECT o_orderpriority, count(*)::BIGINT AS n, sum(l_quantity::BIGINT)::BIGINT AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_sortmerge(t):
    return t("orders").join(t("lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"))


@rel("SELECT s_nationkey, count(*)::BIGINT AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_nationkey")
def join_shuffle_hash(t):
    return t("lineitem").join(t("supplier").hint("shuffle_hash"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("n"))


@rel("SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def join_theta(t):
    a, b = t("region").alias("a"), t("region").alias("b")
    return a.join(b, F.col("a.r_regionkey") < F.col("b.r_regionkey")).select(F.col("a.r_name").alias("a"), F.col("b.r_name").alias("b"))


BANDS = [(0, 10), (10, 50), (50, 200), (200, 10**9)]


@rel("SELECT low::INTEGER AS low, count(*)::BIGINT AS n FROM events JOIN (VALUES (0, 10), (10, 50), (50, 200), (200, 1000000000)) b(low, high) ON value >= low AND value < high GROUP BY low")
def join_range(t):
    e = t("events")
    bands = F.broadcast(e.sparkSession.createDataFrame(BANDS, "low int, high int"))
    return e.join(bands, (F.col("value") >= F.col("low")) & (F.col("value") < F.col("high"))).groupBy("low").agg(F.count(F.lit(1)).alias("n"))


SESSIONS = "s AS (SELECT user_id, event_id AS id, floor(epoch(ts))::BIGINT AS a, floor(epoch(ts))::BIGINT + 1800 AS b FROM events WHERE event_type = 'purchase')"


@rel("WITH " + SESSIONS + " SELECT x.id AS x, y.id AS y FROM s x JOIN s y ON x.id < y.id AND x.a <= y.b AND y.a <= x.b")
def join_interval(t):
    """Overlapping half-hour intervals: an interval stands in each hour it touches, so equal hours meet."""
    s = t("events").where("event_type = 'purchase'").select(F.col("event_id").alias("id"), seconds("ts").alias("a")).withColumn("b", F.col("a") + 1800)
    cells = s.withColumn("cell", F.explode(F.sequence(F.expr("a div 3600"), F.expr("b div 3600"))))
    y = cells.select(F.col("id").alias("y"), F.col("a").alias("ya"), F.col("b").alias("yb"), "cell")
    met = cells.join(y, "cell").where("id < y AND a <= yb AND ya <= b").where("cell = greatest(a, ya) div 3600")  # each pair once, where it begins
    return met.select(F.col("id").alias("x"), "y")


@rel("SELECT p.event_id, (SELECT max_by(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND (v.ts, v.event_id) < (p.ts, p.event_id)) AS view_id FROM events p WHERE p.event_type = 'purchase'")
def join_asof(t):
    """Each purchase with the user's latest view before it, by one window over both."""
    e = t("events").where(F.col("event_type").isin("view", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "view_id")


for _how in ("left", "right", "full"):

    @rel(f"SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.lang, l.toxic FROM (SELECT * FROM documents WHERE lang <> 'en') d {_how.upper()} JOIN labels l ON d.doc_id = l.doc_id", name=f"join_{_how}")
    def _outer(t, how=_how):
        d = t("documents").where("lang <> 'en'").select("doc_id", "lang")
        return d.join(t("labels").select("doc_id", "toxic"), "doc_id", how)


@rel("SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def semi(t):
    return t("documents").select("doc_id", "source").join(t("labels"), "doc_id", "left_semi")


@rel("SELECT doc_id, source FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def anti(t):
    return t("documents").select("doc_id", "source").join(t("labels"), "doc_id", "left_anti")


@rel("SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")
def self_join(t):
    a, b = t("supplier").alias("a"), t("supplier").alias("b")
    return a.join(b, (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey"))).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@rel("SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum(l_quantity::BIGINT)::BIGINT AS qty, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY ALL")
def agg_hash(t):
    return t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"))


@rel("SELECT p_type, max(p_name) AS last_name, min(p_brand) AS first_brand FROM part GROUP BY p_type")
def agg_sort(t):
    return t("part").groupBy("p_type").agg(F.max("p_name").alias("last_name"), F.min("p_brand").alias("first_brand"))


@rel("SELECT event_type, count(DISTINCT user_id)::BIGINT AS users FROM events GROUP BY event_type")
def agg_distinct(t):
    return t("events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@rel()
def approx_distinct(t):
    return t("events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@rel()
def percentile_approx(t):
    return t("events").groupBy("event_type").agg(F.percentile_approx("value", 0.5, 10000).alias("mid"))


@rel("SELECT source, count(*) FILTER (WHERE lang = 'en')::BIGINT AS en, sum(CASE WHEN n_chars > 1000 THEN 1 ELSE 0 END)::BIGINT AS long FROM documents GROUP BY source")
def agg_filter(t):
    return t("documents").groupBy("source").agg(F.count_if(F.col("lang") == "en").alias("en"), F.sum(F.when(F.col("n_chars") > 1000, 1).otherwise(0)).alias("long"))


sql_twin("grouping_sets", "SELECT lang, source, CAST(count(*) AS BIGINT) AS n, CAST(grouping(lang) AS INT) AS g FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")


@rel("SELECT lang, source, count(*)::BIGINT AS n FROM documents GROUP BY CUBE (lang, source)")
def cube(t):
    return t("documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@rel("SELECT lang, source, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def rollup(t):
    return t("documents").rollup("lang", "source").agg(F.sum("n_chars").alias("chars"))


@rel("SELECT user_id, count(*) FILTER (WHERE event_type = 'view')::BIGINT AS view, count(*) FILTER (WHERE event_type = 'click')::BIGINT AS click, count(*) FILTER (WHERE event_type = 'purchase')::BIGINT AS purchase FROM events GROUP BY user_id")
def pivot(t):
    return t("events").groupBy("user_id").pivot("event_type", ["view", "click", "purchase"]).count().na.fill(0, ["view", "click", "purchase"])


@rel("SELECT doc_id, 'quality' AS what, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def unpivot(t):
    return t("labels").unpivot(["doc_id"], ["quality", "toxic"], "what", "v")


@rel("SELECT source, bit_or(n_chars)::BIGINT AS o, bit_and(n_chars)::BIGINT AS a, bit_xor(doc_id)::BIGINT AS x, sum(bit_count(doc_id))::BIGINT AS c FROM documents GROUP BY source")
def bit_aggs(t):
    return t("documents").groupBy("source").agg(F.bit_or("n_chars").alias("o"), F.bit_and("n_chars").alias("a"), F.bit_xor("doc_id").alias("x"), F.sum(F.bit_count("doc_id")).cast("long").alias("c"))


@rel("SELECT lang, array_to_string(list_sort(list(DISTINCT source)), ',') AS sources, max_by(doc_id, (n_chars, doc_id)) AS longest, min_by(doc_id, (n_chars, doc_id)) AS shortest FROM documents GROUP BY lang")
def collect(t):
    order = F.struct("n_chars", "doc_id")
    return t("documents").groupBy("lang").agg(F.array_join(F.array_sort(F.collect_set("source")), ",").alias("sources"), F.max_by("doc_id", order).alias("longest"), F.min_by("doc_id", order).alias("shortest"))


@rel("""SELECT doc_id, row_number() OVER w::INTEGER AS rn, rank() OVER (PARTITION BY source ORDER BY lang)::INTEGER AS rk, dense_rank() OVER (PARTITION BY source ORDER BY lang)::INTEGER AS dr, ntile(4) OVER w::INTEGER AS nt,
 round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id)""".replace(" OVER w::INTEGER", " OVER w").replace("OVER (PARTITION BY source ORDER BY lang)::INTEGER", "OVER (PARTITION BY source ORDER BY lang)"))
def window_rank(t):
    w, v = Window.partitionBy("source").orderBy("n_chars", "doc_id"), Window.partitionBy("source").orderBy("lang")
    return t("documents").select("doc_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@rel("SELECT event_id, floor(epoch(ts))::BIGINT - floor(epoch(lag(ts) OVER w))::BIGINT AS gap, lead(event_type) OVER w AS next, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t("events").select("event_id", (seconds("ts") - seconds(F.lag("ts").over(w))).alias("gap"), F.lead("event_type").over(w).alias("next"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


@rel("SELECT doc_id, sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW)::BIGINT AS recent, min(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN CURRENT ROW AND 15 FOLLOWING) AS low FROM documents")
def window_rows(t):
    w = Window.partitionBy("source").orderBy("doc_id")
    return t("documents").select("doc_id", F.sum("n_chars").over(w.rowsBetween(-3, 0)).alias("recent"), F.min("n_chars").over(w.rowsBetween(0, 15)).alias("low"))


@rel("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def window_range(t):
    w = Window.partitionBy("user_id").orderBy(seconds("ts")).rangeBetween(-3600, 0)
    return t("events").select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@rel("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def topk(t):
    return t("documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


@rel("SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def topk_per_group(t):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return t("documents").withColumn("r", F.row_number().over(w)).where("r <= 3").select("source", "doc_id", "n_chars")


for _name, _op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):

    @rel(f"SELECT s_nationkey AS k FROM supplier {_op} SELECT c_nationkey FROM customer WHERE c_custkey <= 8", name=_name)
    def _set(t, name=_name):
        a, b = t("supplier").select(F.col("s_nationkey").alias("k")), t("customer").where("c_custkey <= 8").select(F.col("c_nationkey").alias("k"))
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.union(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[name]()


@rel("SELECT doc_id, substr(text, 3, 5) AS s, translate(lang, 'aeiou', '12345') AS tr, regexp_replace(source, '[0-9]+', '#') AS rr, regexp_extract(source, '([0-9]+)', 1) AS rx, reverse(source) AS rv, string_split(source, 'r')[1] AS sp, concat_ws('-', lang, source) AS cw, lpad(source, 8, '*') AS lp, instr(source, 'c')::INTEGER AS ins, length(text)::INTEGER AS ln, md5(source) AS m, sha256(lang) AS sh FROM documents")
def fn_string(t):
    c = F.col
    return t("documents").select("doc_id", F.substring("text", 3, 5).alias("s"), F.translate("lang", "aeiou", "12345").alias("tr"), F.regexp_replace("source", "[0-9]+", "#").alias("rr"), F.regexp_extract("source", "([0-9]+)", 1).alias("rx"), F.reverse("source").alias("rv"), F.split("source", "r")[0].alias("sp"), F.concat_ws("-", "lang", "source").alias("cw"), F.lpad("source", 8, "*").alias("lp"), F.instr("source", "c").alias("ins"), F.length("text").alias("ln"), F.md5(c("source").cast("binary")).alias("m"), F.sha2(c("lang").cast("binary"), 256).alias("sh"))


@rel("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, strftime(o_orderdate, '%Y-%m') AS ym, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS dd, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mo, strftime(o_orderdate::DATE + INTERVAL 2 MONTH, '%Y-%m-%d') AS later FROM orders")
def fn_date(t):
    d = F.col("o_orderdate")
    return t("orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.date_format(d, "yyyy-MM").alias("ym"), F.datediff(F.to_date(d), F.lit("1992-01-01").cast("date")).alias("dd"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("mo"), F.date_format(F.add_months(F.to_date(d), 2), "yyyy-MM-dd").alias("later"))


@rel("SELECT doc_id, round(ln(n_chars), 9) AS l, round(exp(1.0 / n_chars), 9) AS e, round(pow(n_chars, 0.5), 6) AS p, round(sqrt(n_chars), 6) AS q, (doc_id - 7) % 5 + CASE WHEN (doc_id - 7) % 5 < 0 THEN 5 ELSE 0 END AS pm, n_chars << 2 AS sl, n_chars >> 3 AS sr FROM documents")
def fn_math(t):
    n = F.col("n_chars")
    return t("documents").select("doc_id", F.round(F.ln(n), 9).alias("l"), F.round(F.exp(1.0 / n), 9).alias("e"), F.round(F.pow(n, F.lit(0.5)), 6).alias("p"), F.round(F.sqrt(n), 6).alias("q"), F.pmod(F.col("doc_id") - 7, F.lit(5)).alias("pm"), F.shiftleft(n, 2).alias("sl"), F.shiftright(n, 3).alias("sr"))


@rel(r"""WITH w AS (SELECT conv_id, turn, list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '') AS w FROM conversations)
SELECT conv_id, turn, len(w)::INTEGER AS n, list_sum(list_transform(w, lambda x: length(x)))::BIGINT AS chars, len(list_filter(w, lambda x: length(x) > 6))::INTEGER AS longs, list_min(w) AS low, list_contains(w, 'the') AS has, len(list_distinct(w))::INTEGER AS d, array_to_string(w[1:3], ' ') AS head FROM w""")
def fn_array(t):
    w = t("conversations").select("conv_id", "turn", F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "").alias("w"))
    return w.select("conv_id", "turn", F.size("w").alias("n"), F.aggregate(F.transform("w", lambda x: F.length(x).cast("long")), F.lit(0).cast("long"), lambda a, b: a + b).alias("chars"), F.size(F.filter("w", lambda x: F.length(x) > 6)).alias("longs"), F.array_min("w").alias("low"), F.exists("w", lambda x: x == "the").alias("has"), F.size(F.array_distinct("w")).alias("d"), F.array_join(F.slice("w", 1, 3), " ").alias("head"))


@rel("SELECT event_id, array_to_string(list_sort(json_keys(props)), ',') AS keys, len(json_keys(props))::INTEGER AS n FROM events")
def fn_map(t):
    m = F.from_json("props", "map<string,string>")
    return t("events").select("event_id", F.array_join(F.array_sort(F.map_keys(m)), ",").alias("keys"), F.size(F.map_filter(m, lambda k, v: k.isNotNull())).alias("n"))


@rel("SELECT event_id, json_extract_string(props, '$.' || (list_sort(json_keys(props))[1])) AS v FROM events")
def fn_json(t):
    m = F.from_json("props", "map<string,string>")
    return t("events").select("event_id", F.get(F.transform(F.array_sort(F.map_keys(m)), lambda k: m[k]), 0).alias("v"))


@rel("SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18,2))::DECIMAL(28,2)::VARCHAR AS total FROM lineitem GROUP BY l_returnflag")
def fn_decimal(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("decimal(28,2)").cast("string").alias("total"))


@rel("SELECT event_id, strftime(ts + INTERVAL 90 MINUTE, '%Y-%m-%d %H:%M:%S') AS later, floor(epoch(ts + INTERVAL 1 DAY))::BIGINT - floor(epoch(ts))::BIGINT AS day FROM events")
def fn_interval(t):
    later = F.col("ts") + F.make_interval(mins=F.lit(90))
    return t("events").select("event_id", F.date_format(later, "yyyy-MM-dd HH:mm:ss").alias("later"), (seconds(F.col("ts") + F.expr("INTERVAL 1 DAY")) - seconds("ts")).alias("day"))


@rel("WITH n AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings), q AS (SELECT * FROM n WHERE vec_id % 100 = 0), s AS (SELECT q.vec_id AS a, n.vec_id AS b, list_cosine_similarity(q.e, n.e) AS c FROM q JOIN n ON q.vec_id <> n.vec_id), r AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY c DESC, b) AS p FROM s) SELECT a, b, round(c, 6) AS c FROM r WHERE p <= 3")
def cosine(t):
    """The three nearest vectors of a stated query set, each hundredth vector, against all."""
    v = t("embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    v = v.withColumn("n", F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x)))
    q = F.broadcast(v.where("vec_id % 100 = 0").select(F.col("vec_id").alias("a"), F.col("e").alias("qe"), F.col("n").alias("qn")))
    s = v.join(q, F.col("a") != F.col("vec_id")).select("a", F.col("vec_id").alias("b"), (F.aggregate(F.zip_with("e", "qe", lambda x, y: x * y), F.lit(0.0), lambda x, y: x + y) / (F.col("n") * F.col("qn"))).alias("c"))
    top = F.slice(F.sort_array(F.collect_list(F.struct("c", (-F.col("b")).alias("b"))), False), 1, 3)
    part = s.groupBy("a", F.pmod(F.col("b"), F.lit(16)).alias("p")).agg(top.alias("k")).select("a", F.explode("k").alias("x")).select("a", F.col("x.c").alias("c"), (-F.col("x.b")).alias("b"))
    return part.groupBy("a").agg(top.alias("k")).select("a", F.explode("k").alias("x")).select("a", (-F.col("x.b")).alias("b"), F.round("x.c", 6).alias("c"))


sql_twin("scalar_subquery", "SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
sql_twin("exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
sql_twin("not_in", "SELECT n_name FROM nation WHERE n_nationkey NOT IN (SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000)")
sql_twin("correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.5 * avg(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
sql_twin("cte", "WITH big AS (SELECT source, sum(n_chars) AS c FROM documents GROUP BY source), top AS (SELECT max(c) AS m FROM big) SELECT source, CAST(c AS BIGINT) AS c FROM big, top WHERE c >= 0.5 * m")


@rel("SELECT doc_id FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % 10 = 3")
def hash_sample(t):
    """A repeatable tenth, by hash: a sampling operator."""
    return t("documents").where(F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % 10 == 3).select("doc_id")


@rel("SELECT conv_id, unnest(string_split(role, 's')) AS part FROM conversations")
def explode(t):
    return t("conversations").select("conv_id", F.explode(F.split("role", "s")).alias("part"))


@rel("SELECT doc_id, unnest(range(0, 2))::INTEGER AS pos, unnest([lang, source]) AS v FROM documents")
def posexplode(t):
    return t("documents").select("doc_id", F.posexplode_outer(F.array("lang", "source")).alias("pos", "v"))


@rel("SELECT r_regionkey, 'key' AS what, r_regionkey::VARCHAR AS v FROM region UNION ALL SELECT r_regionkey, 'name', r_name FROM region")
def stack(t):
    return t("region").select("r_regionkey", F.stack(F.lit(2), F.lit("key"), F.col("r_regionkey").cast("string"), F.lit("name"), F.col("r_name")).alias("what", "v"))


sql_twin("lateral", "SELECT n.n_name, c.k FROM nation n, LATERAL (SELECT CAST(count(*) AS BIGINT) AS k FROM customer WHERE c_nationkey = n.n_nationkey) c")
