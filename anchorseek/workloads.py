"""Registered queries of the methods, their baselines and measures, with DuckDB SQL where it can say the same.

Queries with SQL use the md5 family, which any engine computes alike; the sweeps use xxhash64.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import anchored, grams, hashing, sketch, views
from .operators import baselines, bucket_grid, file_matrix, filters, measures, pages, workload
from .plans import cachesim, theory
from .plans.spec import PAGE_BITS, IndexSpec

K, T = 31, 16
#: Portable parameters: two functions with their own subgram hashes, md5. Values are those of any road; this is the fast one.
SPEC = IndexSpec(m=1 << 23, eta=2, L=4096, seed=7, family="md5", oph=False, backend="arrow")
FAST = IndexSpec(m=1 << 23, eta=4, L=2048)


def table(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


def spread(df):
    """More partitions than files, so that small inputs use all cores; a shuffle of the raw rows, once."""
    spark = df.sparkSession
    wanted = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8)
    return df.repartition(wanted) if df.rdd.getNumPartitions() < wanted else df


def docs(spark, d, file_id=None):
    return views.dna_sequences(table(spark, d, "documents"), file_id=file_id)


def reads(spark, d, file_id=None):
    read = table(spark, d, "documents").select("doc_id", "text", "source", "lang")
    return views.to_reads(views.dna_sequences(read.repartition(F.col("doc_id")), file_id=file_id), K)


def poisoned(spark, d):
    return workload.poison(reads(spark, d, "source"), K)


def _queries(spark, d):
    return poisoned(spark, d).select("query_id", "seq")


# ---------------------------------------------------------------- DuckDB text

LETTERS, DNA = views.LETTERS, views.DNA
SEQS = f"""seqs AS (SELECT doc_id, source, lang, translate(regexp_replace(lower(coalesce(text, '')), '[^a-z]', '', 'g'), '{LETTERS}', '{DNA}') AS s FROM documents)"""


def _at(k):
    return f"unnest(range(1, greatest(len(s) - {k - 1}, 0) + 1))"


def _h(seed, key):
    return f"('0x' || substr(md5('{seed}:' || {key}), 1, 15))::BIGINT"


GRAMS = SEQS + f""",
grams AS (SELECT doc_id, source, lang, p AS i, substr(s, p, {K}) AS g FROM (SELECT *, {_at(K)} AS p FROM seqs))"""


def _places_sql(spec, frame="seqs", keys="doc_id, source, lang"):
    """CTEs that end in places(keys, i, rep, bit) for the sequences s of a frame."""
    parts, arms = [], []
    for j in range(spec.eta):
        s0, s1, s2 = spec.seeds(j)
        if spec.hash != "uniform":
            parts.append(f"""
h{j} AS (SELECT {keys}, p AS i, {_h(s0, f"substr(s, p, {spec.t})")} AS h FROM (SELECT *, {_at(spec.t)} AS p FROM {frame})),
sk{j} AS (SELECT * FROM (SELECT {keys}, i, min(h) OVER w AS v, count(*) OVER w AS n FROM h{j} WINDOW w AS (PARTITION BY {keys} ORDER BY i ROWS BETWEEN CURRENT ROW AND {spec.width - 1} FOLLOWING)) WHERE n = {spec.width})""")
        gram = f"(SELECT *, substr(s, p, {spec.k}) AS g, p AS i FROM (SELECT *, {_at(spec.k)} AS p FROM {frame}))"
        if spec.hash == "uniform":
            arms.append(f"SELECT {keys}, i, {spec.rep_of(j)} AS rep, {_h(s2, 'g')} % {spec.range} AS bit FROM {gram}")
        elif spec.hash == "sketch":
            arms.append(f"SELECT {keys}, i, {spec.rep_of(j)} AS rep, {_h(s1, 'v')} % {spec.range} AS bit FROM sk{j}")
        else:
            names = keys.split(", ")
            same = " AND ".join(f"x.{c} IS NOT DISTINCT FROM y.{c}" for c in names)
            cols = ", ".join(f"x.{c}" for c in names)
            arms.append(f"SELECT {cols}, x.i, {spec.rep_of(j)} AS rep, {_h(s1, 'v')} % {spec.anchors} + {_h(s2, 'g')} % {spec.L} AS bit FROM {gram} x JOIN sk{j} y ON {same} AND x.i = y.i")
    return ",".join(parts) + ("," if parts else "") + "\nplaces AS (" + " UNION ALL ".join(arms) + ")"


def _uniq_keys(spec, frame, keys):
    """places() keyed by one id."""
    return _places_sql(spec, frame, keys)


READ_STEP = 230 - K + 1
POISON = f"""rd AS (SELECT doc_id, source, r AS read_no, substr(s, (r * {READ_STEP} + 1)::BIGINT, 230) AS s, (doc_id * 16777216 + r)::BIGINT AS query_id
  FROM (SELECT *, unnest(range(0, greatest(ceil((len(s) - {K - 1}) / {READ_STEP}.0)::BIGINT, 1))) AS r FROM seqs)),
p1 AS (SELECT *, {K + 1} + ({_h(11, "query_id")} % (least(len(s), 80) - {K})) AS n FROM rd WHERE len(s) > {K}),
p2 AS (SELECT *, {_h(12, "query_id")} % (len(s) - n + 1) AS a, {_h(13, "query_id")} % n AS poison_pos FROM p1),
p3 AS (SELECT *, substr(s, (a + 1)::BIGINT, n::BIGINT) AS clean FROM p2),
p4 AS (SELECT *, substr(clean, (poison_pos + 1)::BIGINT, 1) AS poison_from FROM p3),
p5 AS (SELECT *, substr('ACGT', ((instr('ACGT', poison_from) - 1 + 1 + {_h(14, "query_id")} % 3) % 4 + 1)::BIGINT, 1) AS poison_to FROM p4),
pq AS (SELECT query_id, source AS origin_file, substr(clean, 1, poison_pos::BIGINT) || poison_to || substr(clean, (poison_pos + 2)::BIGINT) AS seq, clean, poison_pos::INTEGER AS poison_pos, poison_from, poison_to,
  (least(poison_pos, n - {K}) - greatest(poison_pos - {K - 1}, 0) + 1)::INTEGER AS n_affected FROM p5)"""

QUERY_GRAMS = f"""qs AS (SELECT query_id, seq AS s FROM pq),
qg AS (SELECT query_id, p AS i, substr(s, p, {K}) AS g FROM (SELECT *, {_at(K)} AS p FROM qs))"""


def _prefixed(text, mark):
    """CTE names of a second set of places, marked."""
    import re

    return re.sub(r"\b(h|sk)(\d)\b", rf"\1{mark}\2", text).replace("places AS", f"places{mark} AS")


def _filter_sql(spec):
    """CTEs up to member(query_id, hit) of the poisoned queries in the filter of all documents."""
    return "WITH " + SEQS + ",\n" + _places_sql(spec) .lstrip(",") + ",\nbits AS (SELECT DISTINCT rep, bit FROM places),\n" + POISON + ",\n" + QUERY_GRAMS + ",\n" + _prefixed(_places_sql(spec, "qs", "query_id"), "q").lstrip(",") + """,
probe AS (SELECT q.query_id, q.i, q.rep, b.bit IS NOT NULL AS ok FROM placesq q LEFT JOIN bits b ON q.rep = b.rep AND q.bit = b.bit)"""


QUERIES, SQL = {}, {}


def register(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# ---------------------------------------------------------------- grams

@register("gram_counts", "WITH " + SEQS + f" SELECT source AS file_id, sum(greatest(len(s) - {K - 1}, 0))::BIGINT AS n_grams, count(*) FILTER (WHERE len(s) < {K})::BIGINT AS too_short FROM seqs GROUP BY source")
def gram_counts(spark, d):
    n = F.greatest(F.length("seq") - (K - 1), F.lit(0))
    return docs(spark, d, "source").groupBy("file_id").agg(F.sum(n).cast("long").alias("n_grams"), F.sum((F.length("seq") < K).cast("long")).alias("too_short"))


@register("gram_sets_per_file", "WITH " + GRAMS + " SELECT source AS file_id, count(DISTINCT g)::BIGINT AS n_distinct FROM grams GROUP BY source")
def gram_sets_per_file(spark, d):
    return grams.gram_set(reads(spark, d, "source"), ["file_id"], "seq", K).groupBy("file_id").agg(F.count(F.lit(1)).alias("n_distinct"))


@register("token_grams", r"""WITH t AS (SELECT conv_id, turn, list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '') AS w FROM conversations),
g AS (SELECT conv_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT *, unnest(range(1, greatest(len(w) - 4, 0) + 1)) AS i FROM t))
SELECT conv_id, count(*)::BIGINT AS n_grams, count(DISTINCT g)::BIGINT AS n_distinct FROM g GROUP BY conv_id""")
def token_grams(spark, d):
    rows = grams.explode_token_grams(views.token_sequences(table(spark, d, "conversations"), keys=("conv_id", "turn")), "tokens", 5)
    return rows.groupBy("conv_id").agg(F.count(F.lit(1)).alias("n_grams"), F.countDistinct("gram").alias("n_distinct"))


@register("log_grams", """WITH l AS (SELECT user_id, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS s FROM events GROUP BY user_id),
g AS (SELECT user_id, substr(s, p, 8) AS g FROM (SELECT *, unnest(range(1, greatest(len(s) - 7, 0) + 1)) AS p FROM l))
SELECT g AS gram, count(*)::BIGINT AS n, count(DISTINCT user_id)::BIGINT AS users FROM g GROUP BY g""")
def log_grams(spark, d):
    rows = grams.explode_grams(views.log_sequences(table(spark, d, "events")), "seq", 8)
    return rows.groupBy("gram").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("seq_id").alias("users"))


@register("pack2", "WITH " + GRAMS + """, c AS (SELECT doc_id, list_reduce(list_transform(string_split(g, ''), lambda x: (instr('ACGT', x) - 1)::BIGINT), lambda a, b: a * 4 + b) AS v FROM grams)
SELECT doc_id, count(*)::BIGINT AS n, min(v)::BIGINT AS lowest, max(v)::BIGINT AS highest, bit_xor(v)::BIGINT AS mixed FROM c GROUP BY doc_id""")
def pack2(spark, d):
    rows = grams.explode_grams(reads(spark, d), "seq", K).select("seq_id", grams.pack2(F.col("gram")).alias("v"))
    return rows.groupBy(F.col("seq_id").alias("doc_id")).agg(F.count(F.lit(1)).alias("n"), F.min("v").alias("lowest"), F.max("v").alias("highest"), F.bit_xor("v").alias("mixed"))


@register("canonical_grams", "WITH " + GRAMS + " SELECT source AS file_id, count(DISTINCT least(g, reverse(translate(g, 'ACGT', 'TGCA'))))::BIGINT AS n_canonical FROM grams GROUP BY source")
def canonical_grams(spark, d):
    rows = grams.explode_grams(reads(spark, d, "source"), "seq", K).select("file_id", grams.canonical(F.col("gram")).alias("g"))
    return rows.distinct().groupBy("file_id").agg(F.count(F.lit(1)).alias("n_canonical"))


@register("reads_overview", "WITH " + SEQS + ",\n" + POISON + " SELECT source AS file_id, count(*)::BIGINT AS n_reads, sum(len(s))::BIGINT AS symbols, sum(greatest(len(s) - 30, 0))::BIGINT AS n_grams FROM rd GROUP BY source")
def reads_overview(spark, d):
    return reads(spark, d, "source").groupBy("file_id").agg(F.count(F.lit(1)).alias("n_reads"), F.sum(F.length("seq")).cast("long").alias("symbols"), F.sum(F.greatest(F.length("seq") - 30, F.lit(0))).cast("long").alias("n_grams"))


# ---------------------------------------------------------------- hashes and positions

def _summary(rows, by=("rep",)):
    return rows.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("bit").alias("n_bits"), F.sum("bit").alias("total"), F.countDistinct(pages.page_of(F.col("bit"))).alias("n_pages"))


SUMMARY = "SELECT rep, count(*)::BIGINT AS n, count(DISTINCT bit)::BIGINT AS n_bits, sum(bit)::BIGINT AS total, count(DISTINCT bit // 32768)::BIGINT AS n_pages FROM places GROUP BY rep"


def _position_query(name, spec):
    @register(name, "WITH " + SEQS + ",\n" + _places_sql(spec).lstrip(",") + " " + SUMMARY)
    def query(spark, d):
        rows = reads(spark, d)
        return filters.summary(rows, spec) if spec.kernel else _summary(anchored.gram_positions(rows, spec))


_position_query("uniform_positions", SPEC.with_(hash="uniform"))
_position_query("sketch_only_positions", SPEC.with_(hash="sketch"))
_position_query("anchored_positions", SPEC)
_position_query("anchored_shared_layout", SPEC.with_(layout="shared"))
_position_query("anchored_t_eq_k", SPEC.with_(t=K, eta=1))
_position_query("anchored_L1", SPEC.with_(L=1, eta=1))
_position_query("anchored_naive", SPEC.with_(eta=1, m=1 << 22, backend="naive"))


@register("modprime_positions", "WITH " + GRAMS + """, c AS (SELECT list_reduce(list_transform(string_split(g, ''), lambda x: (instr('ACGT', x) - 1)::BIGINT), lambda a, b: a * 4 + b) AS v FROM grams),
p AS (SELECT (({a1}::BIGINT * (v & 2147483647) % 2147483647 + {a2}::BIGINT * (v >> 31) % 2147483647 + {b}::BIGINT) % 2147483647) % 4194304 AS bit FROM c)
SELECT count(*)::BIGINT AS n, count(DISTINCT bit)::BIGINT AS n_bits, sum(bit)::BIGINT AS total FROM p""".replace("{a1}", str(hashing.modprime_draw(5)[0])).replace("{a2}", str(hashing.modprime_draw(5)[1])).replace("{b}", str(hashing.modprime_draw(5)[2])))
def modprime_positions(spark, d):
    rows = grams.explode_grams(reads(spark, d), "seq", K).select(hashing.modprime(grams.pack2(F.col("gram")), 5, 1 << 22).alias("bit"))
    return rows.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("bit").alias("n_bits"), F.sum("bit").alias("total"))


SKETCH_SQL = "WITH " + SEQS + ",\n" + _places_sql(SPEC.with_(eta=1, m=1 << 22)).lstrip(",") + " SELECT doc_id, count(*)::BIGINT AS n, count(DISTINCT v)::BIGINT AS n_values, min(v)::BIGINT AS lowest, bit_xor(v)::BIGINT AS mixed FROM sk0 GROUP BY doc_id"


def _sketch_summary(rows):
    return rows.groupBy(F.col("seq_id").alias("doc_id")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("sketch").alias("n_values"), F.min("sketch").alias("lowest"), F.bit_xor("sketch").alias("mixed"))


@register("gram_sketch", SKETCH_SQL)
def gram_sketch(spark, d):
    """Every gram's sketch from scratch: the reference road."""
    rows = grams.explode_grams(reads(spark, d), "seq", K).select("seq_id", sketch.gram_sketch(F.col("gram"), T, 7, "md5", False).alias("sketch"))
    return _sketch_summary(rows)


@register("rolling_sketch_window", SKETCH_SQL)
def rolling_sketch_window(spark, d):
    return _sketch_summary(sketch.windowed_sketch(reads(spark, d), SPEC.with_(eta=1)))


@register("rolling_sketch_doubling", SKETCH_SQL)
def rolling_sketch_doubling(spark, d):
    rows = reads(spark, d).select("seq_id", F.explode(F.get(sketch.sketch_arrays(F.col("seq"), SPEC.with_(eta=1)), 0)).alias("sketch"))
    return _sketch_summary(rows)


#: The default road, Arrow kernel and one-permutation bins, with hashes that any SQL engine computes.
KERNEL = FAST.with_(family="modprime")


def _mod(key, seed, m):
    """modprime in SQL."""

    def one(s):
        a1, a2, b = hashing.modprime_draw(s)
        return f"(({a1}::BIGINT * (({key}) & 2147483647)) % 2147483647 + ({a2}::BIGINT * (({key}) >> 31)) % 2147483647 + {b}::BIGINT) % 2147483647"

    return f"(({one(seed)}) % {m})" if m <= hashing.PRIME else f"((({one(seed)}) * 2147483648 + ({one(seed + 7919)})) % {m})"


def _bins_sql(spec):
    """CTEs that end in places(rep, bit) under one-permutation sketches of modprime hashes."""
    number = lambda text: f"list_reduce(list_transform(string_split({text}, ''), lambda x: (instr('ACGT', x) - 1)::BIGINT), lambda a, b: a * 4 + b)"
    lowest = ", ".join(f"min(CASE WHEN h % {spec.eta} = {b} THEN h // {spec.eta} END) OVER w AS m{b}" for b in range(spec.eta))
    filled = ", ".join("coalesce(" + ", ".join(f"m{(b + s) % spec.eta} + {s * sketch.BORROW}" for s in range(spec.eta)) + f") AS s{b}" for b in range(spec.eta))
    arms = " UNION ALL ".join(f"SELECT {spec.rep_of(j)} AS rep, {_mod(f's{j}', spec.seeds(j)[1], spec.anchors)} + {_mod('g', spec.seeds(j)[2], spec.L)} AS bit FROM sk JOIN gr USING (doc_id, i)" for j in range(spec.eta))
    return f"""sub AS (SELECT doc_id, p AS i, {number(f"substr(s, p, {spec.t})")} AS v FROM (SELECT *, {_at(spec.t)} AS p FROM seqs)),
hs AS (SELECT doc_id, i, {_mod('v', spec.seeds(0)[0], 1 << 61)} AS h FROM sub),
mn AS (SELECT doc_id, i, count(*) OVER w AS c, {lowest} FROM hs WINDOW w AS (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND {spec.width - 1} FOLLOWING)),
sk AS (SELECT doc_id, i, {filled} FROM mn WHERE c = {spec.width}),
gr AS (SELECT doc_id, p AS i, {number(f"substr(s, p, {spec.k})")} AS g FROM (SELECT *, {_at(spec.k)} AS p FROM seqs)),
places AS ({arms})"""


def _kernel_check(backend):
    def query(spark, d):
        return _summary(anchored.gram_positions(reads(spark, d), KERNEL.with_(backend=backend)))

    return query


BINS_SQL = "WITH " + SEQS + ",\n" + _bins_sql(KERNEL) + " " + SUMMARY
register("rolling_sketch_kernel", BINS_SQL)(_kernel_check("arrow"))
register("rolling_sketch_segment_tree", BINS_SQL)(_kernel_check("segment_tree"))
register("oph_sketch_positions", BINS_SQL)(_kernel_check("sql"))


@register("kernel_filter_pages", "WITH " + SEQS + ",\n" + _bins_sql(KERNEL) + " SELECT rep, bit // 32768 AS page_no, count(DISTINCT bit)::BIGINT AS n_bits FROM places GROUP BY ALL")
def kernel_filter_pages(spark, d):
    """Pages that the kernel builds by density, and the bits set in each."""
    return filters.build(reads(spark, d), KERNEL).select("rep", "page_no", F.bitmap_count("bits").alias("n_bits"))


@register("minwise_exact_perm", r"""WITH t AS (SELECT conv_id, turn, list_distinct(list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '')) AS w FROM conversations),
u AS (SELECT DISTINCT unnest(w) AS item FROM t), perm AS (SELECT item, row_number() OVER (ORDER BY md5(item), item) - 1 AS rank FROM u)
SELECT conv_id, turn, min(rank)::BIGINT AS minwise FROM (SELECT conv_id, turn, unnest(w) AS item FROM t) JOIN perm USING (item) GROUP BY ALL""")
def minwise_exact_perm(spark, d):
    from pyspark.sql import Window

    t = views.token_sequences(table(spark, d, "conversations"), keys=("conv_id", "turn")).withColumn("k", F.struct("conv_id", "turn"))
    u = t.select(F.explode("tokens").alias("item")).distinct()
    perm = u.withColumn("rank", (F.row_number().over(Window.orderBy(F.md5(F.col("item").cast("binary")), "item")) - 1).cast("long"))
    return sketch.minwise_perm(t, perm, "k", "tokens").select("k.conv_id", "k.turn", "minwise")


PLANES = sketch.unit_planes(12, 64, 3)


def _plane_bits():
    return " + ".join(f"(CASE WHEN list_dot_product(e, {p}::DOUBLE[]) > 0 THEN {1 << i} ELSE 0 END)" for i, p in enumerate(PLANES))


@register("sign_projection_anchored", f"""WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings), s AS (SELECT vec_id, ({_plane_bits()})::BIGINT AS phi FROM v)
SELECT vec_id, phi, {_h(8, 'phi')} % (1048576 - 1024 + 1) + {_h(9, 'vec_id')} % 1024 AS pos FROM s""")
def sign_projection_anchored(spark, d):
    rows = table(spark, d, "embeddings").select("vec_id", sketch.sign_projection(F.col("embedding"), PLANES).alias("phi"))
    return rows.select("vec_id", "phi", anchored.position(F.col("vec_id"), F.col("phi"), 1 << 20, 1024, 7, "md5").alias("pos"))


@register("stable_projection_anchored", f"""WITH s AS (SELECT vec_id, floor((list_dot_product(list_transform(embedding, lambda x: x::DOUBLE), {PLANES[0]}::DOUBLE[]) + 0.125) / 0.5)::BIGINT AS phi FROM embeddings)
SELECT vec_id, phi, {_h(8, 'phi')} % (1048576 - 1024 + 1) + {_h(9, 'vec_id')} % 1024 AS pos FROM s""")
def stable_projection_anchored(spark, d):
    rows = table(spark, d, "embeddings").select("vec_id", sketch.stable_projection(F.col("embedding"), PLANES[0], 0.125, 0.5).alias("phi"))
    return rows.select("vec_id", "phi", anchored.position(F.col("vec_id"), F.col("phi"), 1 << 20, 1024, 7, "md5").alias("pos"))


@register("collision_rates", "WITH " + GRAMS + f""", d AS (SELECT DISTINCT g FROM grams), v AS (SELECT {_h(9, 'g')} % 4194304 AS v, count(*) AS c FROM d GROUP BY 1), s AS (SELECT sum(c)::BIGINT AS keys, sum(c * (c - 1) // 2)::BIGINT AS colliding FROM v)
SELECT keys, (keys * (keys - 1) // 2)::BIGINT AS pairs, colliding, colliding / (keys * (keys - 1) // 2) AS rate FROM s""")
def collision_rates(spark, d):
    return measures.gram_collision_rate(reads(spark, d), K, 9, 1 << 22)


# ---------------------------------------------------------------- filters

def _index(spark, d, spec):
    return filters.build(reads(spark, d), spec, combine="pages" if spec.kernel else "bits")


for _h_name in ("uniform", "sketch", "anchored"):
    _spec = SPEC.with_(hash=_h_name)

    @register(f"filter_pages_popcount_{_h_name}", "WITH " + SEQS + ",\n" + _places_sql(_spec).lstrip(",") + " SELECT 'all' AS filter_id, rep, count(DISTINCT bit // 32768)::BIGINT AS n_pages, count(DISTINCT bit)::BIGINT AS n_bits FROM places GROUP BY rep")
    def _popcount(spark, d, spec=_spec):
        return _index(spark, d, spec).groupBy("filter_id", "rep").agg(F.count(F.lit(1)).alias("n_pages"), F.sum(F.bitmap_count("bits")).alias("n_bits"))

    @register(f"filter_mt_{_h_name}", _filter_sql(_spec) + " SELECT query_id, bool_and(ok) AS hit FROM probe GROUP BY query_id")
    def _mt(spark, d, spec=_spec):
        return filters.contains(_index(spark, d, spec), _queries(spark, d), spec)

    @register(f"filter_gram_probe_{_h_name}", _filter_sql(_spec) + ", g AS (SELECT query_id, i, bool_and(ok) AS hit FROM probe GROUP BY ALL) SELECT query_id, count(*)::BIGINT AS n, count(*) FILTER (WHERE hit)::BIGINT AS n_hit, coalesce(min(i) FILTER (WHERE NOT hit) - 1, -1)::INTEGER AS first_miss FROM g GROUP BY query_id")
    def _gram_probe(spark, d, spec=_spec):
        rows = filters.probe_grams(_index(spark, d, spec), _queries(spark, d), spec)
        return rows.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("hit").cast("long")).alias("n_hit"), F.coalesce(F.min(F.when(~F.col("hit"), F.col("pos"))), F.lit(-1)).cast("int").alias("first_miss"))


@register("filter_coverage", _filter_sql(SPEC) + ", g AS (SELECT query_id, i, bool_and(ok) AS hit FROM probe GROUP BY ALL) SELECT query_id, count(*)::BIGINT AS n_grams, count(*) FILTER (WHERE hit)::BIGINT AS n_hit, count(*) FILTER (WHERE hit) / count(*) AS coverage FROM g GROUP BY query_id")
def filter_coverage(spark, d):
    return filters.coverage(_index(spark, d, SPEC), _queries(spark, d), SPEC)


@register("filter_theta", _filter_sql(SPEC) + ", g AS (SELECT query_id, i, bool_and(ok) AS hit FROM probe GROUP BY ALL) SELECT query_id, count(*) FILTER (WHERE hit) / count(*) >= 0.6 AS hit FROM g GROUP BY query_id")
def filter_theta(spark, d):
    return filters.contains(_index(spark, d, SPEC), _queries(spark, d), SPEC.with_(theta=0.6))


MT_SQL = _filter_sql(SPEC) + " SELECT query_id, bool_and(ok) AS hit FROM probe GROUP BY query_id"


@register("filter_early_exit_rounds", MT_SQL)
def filter_early_exit_rounds(spark, d):
    return filters.contains(_index(spark, d, SPEC), _queries(spark, d), SPEC.with_(exit="rounds"))


@register("filter_early_exit_kernel", MT_SQL)
def filter_early_exit_kernel(spark, d):
    return filters.contains(_index(spark, d, SPEC), _queries(spark, d), SPEC.with_(exit="kernel"))


@register("filter_union", "WITH " + SEQS + ",\n" + _places_sql(SPEC).lstrip(",") + " SELECT rep, bit // 32768 AS page_no, count(DISTINCT bit)::BIGINT AS n_bits FROM places GROUP BY ALL")
def filter_union(spark, d):
    """The filters of two halves of the documents, joined, are the filter of all."""
    rows = reads(spark, d)
    half = F.col("seq_id") % 2 == 0
    a, b = (filters.build(rows.where(c), SPEC, combine="bits") for c in (half, ~half))
    return filters.union(a, b, SPEC, SPEC).select("rep", "page_no", F.bitmap_count("bits").alias("n_bits"))


@register("filter_fill", "WITH " + SEQS + ",\n" + _places_sql(SPEC).lstrip(",") + f" SELECT 'all' AS filter_id, rep, count(DISTINCT bit)::BIGINT AS n_bits, count(DISTINCT bit) / {SPEC.range} AS fill FROM places GROUP BY rep")
def filter_fill(spark, d):
    return filters.fill(_index(spark, d, SPEC), SPEC)


@register("index_size", "WITH " + SEQS + ",\n" + _places_sql(SPEC).lstrip(",") + f" SELECT count(*)::BIGINT AS stored_pages, count(*)::BIGINT * 4096 AS stored_bytes, {SPEC.m // 8}::BIGINT AS nominal_bytes FROM (SELECT DISTINCT rep, bit // 32768 AS p FROM places)")
def index_size(spark, d):
    return measures.index_size(_index(spark, d, SPEC), SPEC.m, 1)


# ---------------------------------------------------------------- many sets

def _matrix_sql(spec, cond=""):
    return "WITH " + SEQS + ",\n" + _places_sql(spec).lstrip(",") + ",\nbits AS (SELECT DISTINCT rep, bit, source AS file_id FROM places),\n" + POISON + ",\n" + QUERY_GRAMS + ",\n" + _prefixed(_places_sql(spec, "qs", "query_id"), "q").lstrip(",") + """,
need AS (SELECT query_id, count(*) AS n FROM (SELECT DISTINCT query_id, rep, bit FROM placesq) GROUP BY 1),
have AS (SELECT query_id, file_id, count(*) AS n FROM (SELECT DISTINCT query_id, rep, bit FROM placesq) JOIN bits USING (rep, bit) GROUP BY ALL),
msmt AS (SELECT q.query_id, f.file_id, coalesce(h.n, 0) = n.n AS hit FROM need n JOIN qs q USING (query_id) CROSS JOIN (SELECT DISTINCT source AS file_id FROM seqs) f LEFT JOIN have h ON h.query_id = q.query_id AND h.file_id = f.file_id)"""


WIDE = SPEC.with_(eta=1, m=1 << 20)
for _h_name in ("uniform", "anchored"):
    _spec = WIDE.with_(hash=_h_name)

    @register(f"filematrix_msmt_{_h_name}", _matrix_sql(_spec) + " SELECT * FROM msmt")
    def _msmt(spark, d, spec=_spec):
        return file_matrix.search(file_matrix.build(reads(spark, d, "source"), spec), _queries(spark, d))


@register("filematrix_files_layout", _matrix_sql(WIDE) + " SELECT * FROM msmt")
def filematrix_files_layout(spark, d):
    return file_matrix.search(file_matrix.build(reads(spark, d, "source"), WIDE, "files"), _queries(spark, d))


@register("filematrix_bitmap_layout", _matrix_sql(WIDE) + " SELECT * FROM msmt")
def filematrix_bitmap_layout(spark, d):
    return file_matrix.search(file_matrix.build(reads(spark, d, "source"), WIDE, "bitmap"), _queries(spark, d))


@register("filematrix_coverage_topk", "WITH " + SEQS + ",\n" + _places_sql(WIDE).lstrip(",") + ",\nbits AS (SELECT DISTINCT rep, bit, source AS file_id FROM places),\n" + POISON + ",\n" + QUERY_GRAMS + ",\n" + _prefixed(_places_sql(WIDE, "qs", "query_id"), "q").lstrip(",") + """,
c AS (SELECT query_id, file_id, count(*)::BIGINT AS n_hit FROM placesq JOIN bits USING (rep, bit) GROUP BY ALL),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY n_hit DESC, file_id) AS place FROM c)
SELECT query_id, file_id, n_hit, place::INTEGER AS place FROM r WHERE place <= 3""")
def filematrix_coverage_topk(spark, d):
    """The three files that hold most grams of each query."""
    return file_matrix.top(file_matrix.build(reads(spark, d, "source"), WIDE), _queries(spark, d), 3)


@register("filematrix_disk", _matrix_sql(WIDE) + " SELECT * FROM msmt")
def filematrix_disk(spark, d):
    """The same with the index written, and read again in a fresh plan."""
    from .sources import index_store

    rows = reads(spark, d, "source")
    built = file_matrix.build(rows, WIDE, "files")
    path = index_store.scratch(spark, "file-matrix")
    index_store.write_index(built.rows, WIDE, path)
    pages_, spec = index_store.read_index(spark, path)
    return file_matrix.search(file_matrix.FileMatrix(pages_, built.files, spec, "files", built.few), _queries(spark, d))


def _bucket(col, r, B):
    return f"{_h(SPEC.seed + 1000 + r, col)} % {B}"


GRID_MAP = "bm AS (" + " UNION ALL ".join(f"SELECT {r} AS grid_rep, ({_bucket('file_id', r, 20)})::INTEGER AS bucket, file_id FROM (SELECT DISTINCT lang || '/' || source AS file_id FROM seqs)" for r in range(2)) + ")"


def _grid_reads(spark, d):
    return reads(spark, d, F.concat_ws("/", "lang", "source"))


@register("grid_bucket_map", "WITH " + SEQS + ",\n" + GRID_MAP + " SELECT * FROM bm")
def grid_bucket_map(spark, d):
    return bucket_grid.bucket_map(views.numbered_files(docs(spark, d, F.concat_ws("/", "lang", "source"))), 20, 2, SPEC.seed, "md5")


def _grid_sql(spec):
    return "WITH " + SEQS + ",\n" + GRID_MAP + ",\n" + _places_sql(spec).lstrip(",") + ",\nbits AS (SELECT DISTINCT bm.grid_rep, bm.bucket, rep, bit FROM places JOIN bm ON bm.file_id = lang || '/' || source),\n" + POISON + ",\n" + QUERY_GRAMS + ",\n" + _prefixed(_places_sql(spec, "qs", "query_id"), "q").lstrip(",") + """,
need AS (SELECT query_id, count(*) AS n FROM (SELECT DISTINCT query_id, rep, bit FROM placesq) GROUP BY 1),
have AS (SELECT query_id, grid_rep, bucket, count(*) AS n FROM (SELECT DISTINCT query_id, rep, bit FROM placesq) JOIN bits USING (rep, bit) GROUP BY ALL),
bh AS (SELECT query_id, grid_rep, bucket FROM have JOIN need USING (query_id) WHERE have.n = need.n),
fh AS (SELECT query_id, file_id FROM bh JOIN bm USING (grid_rep, bucket) GROUP BY ALL HAVING count(DISTINCT grid_rep) = 2)
SELECT q.query_id, f.file_id, fh.query_id IS NOT NULL AS hit FROM qs q CROSS JOIN (SELECT DISTINCT file_id FROM bm) f LEFT JOIN fh ON fh.query_id = q.query_id AND fh.file_id = f.file_id"""


for _h_name in ("uniform", "anchored"):
    _spec = WIDE.with_(hash=_h_name, m=1 << 22)

    @register(f"grid_msmt_{_h_name}", _grid_sql(_spec))
    def _grid(spark, d, spec=_spec):
        return bucket_grid.search(bucket_grid.build(_grid_reads(spark, d), spec, 20, 2), _queries(spark, d))


EXACT_FILES = "WITH " + SEQS + ", grams AS (SELECT DISTINCT {file} AS file_id, substr(s, p, 31) AS g FROM (SELECT *, " + _at(K) + " AS p FROM seqs)),\n" + POISON + ",\n" + QUERY_GRAMS + """,
need AS (SELECT query_id, count(DISTINCT g) AS n FROM qg GROUP BY 1), have AS (SELECT query_id, file_id, count(*) AS n FROM (SELECT DISTINCT query_id, g FROM qg) JOIN grams USING (g) GROUP BY ALL)
SELECT q.query_id, f.file_id, coalesce(have.n, 0) = need.n AS hit FROM need JOIN qs q USING (query_id) CROSS JOIN (SELECT DISTINCT {file} AS file_id FROM seqs) f LEFT JOIN have ON have.query_id = q.query_id AND have.file_id = f.file_id"""


@register("grid_refined", EXACT_FILES.replace("{file}", "lang || '/' || source"))
def grid_refined(spark, d):
    """Grid candidates checked on exact grams: the exact answer."""
    rows = _grid_reads(spark, d)
    spec = IndexSpec(m=1 << 22, eta=2, L=2048)
    return bucket_grid.refine(bucket_grid.search(bucket_grid.build(rows, spec, 20, 2), _queries(spark, d)), _queries(spark, d), rows, K)


# ---------------------------------------------------------------- exact references

@register("exact_mt", "WITH " + GRAMS + ",\n" + POISON + ",\n" + QUERY_GRAMS + " SELECT query_id, bool_and(k.g IS NOT NULL) AS hit FROM qg LEFT JOIN (SELECT DISTINCT g FROM grams) k USING (g) GROUP BY query_id")
def exact_mt(spark, d):
    return baselines.exact_mt(reads(spark, d), _queries(spark, d), K, "dna")


@register("exact_msmt", EXACT_FILES.replace("{file}", "source"))
def exact_msmt(spark, d):
    return baselines.exact_msmt(reads(spark, d, "source"), _queries(spark, d), K, "dna")


@register("native_bloom_baseline", SQL["exact_mt"])
def native_bloom_baseline(spark, d):
    return baselines.native_bloom(reads(spark, d), _queries(spark, d), K)


@register("native_filter_errors", "WITH " + GRAMS + ",\n" + POISON + ",\n" + QUERY_GRAMS + ", truth AS (SELECT query_id, bool_and(k.g IS NOT NULL) AS hit FROM qg LEFT JOIN (SELECT DISTINCT g FROM grams) k USING (g) GROUP BY query_id) SELECT count(*) FILTER (WHERE hit)::BIGINT AS members, 0::BIGINT AS missed, count(*) FILTER (WHERE NOT hit)::BIGINT AS negatives, true AS rate_within FROM truth")
def native_filter_errors(spark, d):
    """Spark's own Bloom filters alone: members and those they miss, others and whether under 1 in 100 of them pass."""
    rows, q = reads(spark, d), _queries(spark, d)
    truth = baselines.exact_mt(rows, q, K, "dna").withColumnRenamed("hit", "truth")
    both = baselines.native_mt_parts(rows, q, K).join(truth, "query_id")
    truth, hit = F.col("truth"), F.col("hit")
    negatives = F.count_if(~truth)
    return both.agg(F.count_if(truth).alias("members"), F.count_if(truth & ~hit).alias("missed"), negatives.alias("negatives"), (F.count_if(~truth & hit) * 100 <= negatives).alias("rate_within"))


BENCH_SEQS = f"bs AS (SELECT item_id, translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), '{LETTERS}', '{DNA}') AS q FROM benchmark)"


@register("substring_scan", "WITH " + SEQS + ", " + BENCH_SEQS + " SELECT item_id AS query_id, EXISTS (SELECT 1 FROM seqs WHERE contains(s, q)) AS hit FROM bs")
def substring_scan(spark, d):
    """Whole benchmark items looked up in the documents."""
    items = table(spark, d, "benchmark").select(F.col("item_id").alias("query_id"), views.dna(F.col("text")).alias("seq"))
    return baselines.substring_scan(docs(spark, d), items)


@register("poison_queries", "WITH " + SEQS + ",\n" + POISON + " SELECT * FROM pq")
def poison_queries(spark, d):
    return poisoned(spark, d)


# ---------------------------------------------------------------- measures

FPR_SQL = ", a AS (SELECT query_id, bool_and(ok) AS hit FROM probe GROUP BY query_id), known AS (SELECT DISTINCT substr(s, p, 31) AS g FROM (SELECT *, " + _at(K) + " AS p FROM seqs)), tr AS (SELECT query_id, bool_and(k.g IS NOT NULL) AS truth FROM qg LEFT JOIN known k USING (g) GROUP BY query_id)"


@register("fpr_mt", _filter_sql(SPEC) + FPR_SQL + " SELECT count(*)::BIGINT AS negatives, count(*) FILTER (WHERE hit)::BIGINT AS false_hits, avg(hit::INTEGER) AS fpr FROM a JOIN tr USING (query_id) WHERE NOT truth")
def fpr_mt(spark, d):
    q = _queries(spark, d)
    return measures.fpr_mt(filters.contains(_index(spark, d, SPEC), q, SPEC), baselines.exact_mt(reads(spark, d), q, K, "dna"))


@register("fpr_by_affected_grams", _filter_sql(SPEC) + FPR_SQL + " SELECT n_affected, count(*)::BIGINT AS negatives, count(*) FILTER (WHERE hit)::BIGINT AS false_hits, avg(hit::INTEGER) AS fpr FROM a JOIN tr USING (query_id) JOIN pq USING (query_id) WHERE NOT truth GROUP BY n_affected")
def fpr_by_affected_grams(spark, d):
    p = poisoned(spark, d)
    q = p.select("query_id", "seq")
    return measures.fpr_by(filters.contains(_index(spark, d, SPEC), q, SPEC), baselines.exact_mt(reads(spark, d), q, K, "dna"), p, "n_affected")


MEMBERS = "WITH " + SEQS + ",\n" + POISON + " SELECT kind, count(*)::BIGINT AS members, 0::BIGINT AS missed FROM pq CROSS JOIN (VALUES {kinds}) v(kind) GROUP BY kind"


def _missed(answers, members, kind, keys=("query_id",)):
    """Members, and those of them that an index does not find."""
    seen = members.join(answers.where("hit").select(*keys).distinct().withColumn("_f", F.lit(1)), list(keys), "left")
    return seen.agg(F.count(F.lit(1)).alias("members"), F.sum(F.col("_f").isNull().cast("long")).alias("missed")).select(F.lit(kind).alias("kind"), "members", "missed")


@register("false_negatives", MEMBERS.replace("{kinds}", "('uniform'), ('sketch'), ('anchored')"))
def false_negatives(spark, d):
    """Unchanged pieces, and how many of them each filter does not find: none."""
    twins = workload.clean_twins(poisoned(spark, d)).select("query_id", "seq").cache()
    rows, out = reads(spark, d).cache(), None
    for h in ("uniform", "sketch", "anchored"):
        spec = FAST.with_(hash=h)
        got = _missed(filters.contains(filters.build(rows, spec), twins, spec), twins.select("query_id"), h)
        out = got if out is None else out.unionByName(got)
    return out


@register("facade_members", MEMBERS.replace("{kinds}", "('plain'), ('matrix'), ('grid')"))
def facade_members(spark, d):
    """Unchanged pieces asked of the three kinds of index by their short way, over reads of many files."""
    from .index import Index

    twins = workload.clean_twins(poisoned(spark, d)).cache()
    rows, out = reads(spark, d, "source").cache(), None
    for kind in ("plain", "matrix", "grid"):
        answers = Index(FAST.with_(eta=2, m=1 << 22), kind).fit(rows).search(twins.select("query_id", "seq"))
        members = twins.select("query_id", F.col("origin_file").alias("file_id")) if kind != "plain" else twins.select("query_id")
        got = _missed(answers, members, kind, ("query_id",) if kind == "plain" else ("query_id", "file_id"))
        out = got if out is None else out.unionByName(got)
    return out


@register("fpr_msmt", _matrix_sql(WIDE) + ", known AS (SELECT DISTINCT source AS file_id, substr(s, p, 31) AS g FROM (SELECT *, " + _at(K) + " AS p FROM seqs)), dq AS (SELECT DISTINCT query_id, g FROM qg), nd AS (SELECT query_id, count(*) AS n FROM dq GROUP BY 1), hv AS (SELECT query_id, file_id, count(*) AS n FROM dq JOIN known USING (g) GROUP BY ALL), x AS (SELECT m.file_id, m.hit FROM msmt m JOIN nd USING (query_id) LEFT JOIN hv ON hv.query_id = m.query_id AND hv.file_id = m.file_id WHERE coalesce(hv.n, 0) <> nd.n), per AS (SELECT file_id, count(*) AS n, count(*) FILTER (WHERE hit) AS f FROM x GROUP BY 1) SELECT count(*)::BIGINT AS files, avg(f / n) AS macro_fpr, sum(f) / sum(n) AS pooled_fpr FROM per")
def fpr_msmt(spark, d):
    rows, q = reads(spark, d, "source"), _queries(spark, d)
    return measures.fpr_msmt(file_matrix.search(file_matrix.build(rows, WIDE), q), baselines.exact_msmt(rows, q, K, "dna"))


@register("fpr_gram", _filter_sql(SPEC) + ", known AS (SELECT DISTINCT substr(s, p, 31) AS g FROM (SELECT *, " + _at(K) + " AS p FROM seqs)), a AS (SELECT query_id, i, bool_and(ok) AS hit FROM probe GROUP BY ALL) SELECT count(*)::BIGINT AS negatives, count(*) FILTER (WHERE hit)::BIGINT AS false_hits, avg(hit::INTEGER) AS fpr FROM a JOIN qg USING (query_id, i) LEFT JOIN known k USING (g) WHERE k.g IS NULL")
def fpr_gram(spark, d):
    q = _queries(spark, d)
    return measures.fpr_gram(filters.probe_grams(_index(spark, d, SPEC), q, SPEC), baselines.exact_grams(reads(spark, d), q, K))


@register("subgram_jaccard_by_gap")
def subgram_jaccard_by_gap(spark, d):
    return measures.jaccard_by_gap(reads(spark, d), K, T, alphabet="dna")


FAR = f"""f1 AS (SELECT source, doc_id, s, len(s) - {K - 1} AS n, unnest([1, 2, 3, 4]) AS draw FROM seqs WHERE len(s) - {K - 1} > {K}),
f2 AS (SELECT *, {_h(3, "doc_id || '/' || draw")} % (n - {K}) AS a FROM f1), f3 AS (SELECT *, a + {K} + {_h(4, "doc_id || '/' || draw")} % (n - {K} - a) AS b FROM f2),
f4 AS (SELECT source, list_transform(range(1, {K - T + 2}), lambda i: substr(s, (a + i)::BIGINT, {T})) AS x, list_transform(range(1, {K - T + 2}), lambda i: substr(s, (b + i)::BIGINT, {T})) AS y FROM f3)"""


@register("far_pair_zero_rate", "WITH " + SEQS + ",\n" + FAR + " SELECT source AS file_id, count(*)::BIGINT AS pairs, avg((NOT list_has_any(x, y))::INTEGER) AS zero_rate FROM f4 GROUP BY source")
def far_pair_zero_rate(spark, d):
    return measures.far_pair_zero_rate(docs(spark, d, "source"), K, T)


@register("similar_gram_counts", "WITH " + SEQS + ", " + BENCH_SEQS + f""", sub AS (SELECT doc_id, p AS place, len(s) AS n, substr(s, p, {T}) AS sub FROM (SELECT *, {_at(T)} AS p FROM seqs WHERE len(s) >= {K})),
qg AS (SELECT item_id, p AS pos, substr(s, p, {K}) AS g FROM (SELECT *, {_at(K)} AS p FROM (SELECT item_id, q AS s FROM bs))),
qsub AS (SELECT DISTINCT item_id, pos, substr(g, i, {T}) AS sub FROM (SELECT *, unnest(range(1, {K - T + 2})) AS i FROM qg)),
met AS (SELECT DISTINCT item_id, pos, doc_id, unnest(range(greatest(place - {K - T}, 1), least(place, n - {K - 1}) + 1)) AS at_gram FROM qsub JOIN sub USING (sub)),
per AS (SELECT item_id, pos, count(*) AS c FROM met GROUP BY ALL)
SELECT item_id AS query_id, max(c)::BIGINT AS most_similar, {theory.similar_bound(K, T)}::INTEGER AS bound FROM per GROUP BY item_id""")
def similar_gram_counts(spark, d):
    """Grams that share a subgram with a gram of a benchmark item, at most, beside the bound of the lemma."""
    items = table(spark, d, "benchmark").select(F.col("item_id").alias("query_id"), views.dna(F.col("text")).alias("seq"))
    return measures.similar_count(reads(spark, d), items, K, T).withColumn("bound", F.lit(theory.similar_bound(K, T)))


@register("page_locality", "WITH " + SEQS + ",\n" + POISON + ",\n" + QUERY_GRAMS + ",\n" + _places_sql(SPEC, "qs", "query_id").lstrip(",") + ", c AS (SELECT *, coalesce((lag(bit // 32768) OVER (PARTITION BY query_id, rep ORDER BY i, bit) <> bit // 32768)::INTEGER, 1) AS ch FROM places), per AS (SELECT query_id, rep, count(*) AS n, count(DISTINCT bit // 32768) AS dd, sum(ch) AS c FROM c GROUP BY ALL) SELECT sum(n)::BIGINT AS accesses, sum(dd)::BIGINT AS distinct_blocks, sum(c)::BIGINT AS changes, sum(dd) / sum(n) AS blocks_per_access, sum(c) / sum(n) AS changes_per_access FROM per")
def page_locality(spark, d):
    return measures.locality(anchored.gram_positions(_queries(spark, d), SPEC, ["query_id"]))


@register("line_transitions", SQL["page_locality"].replace("32768", "512"))
def line_transitions(spark, d):
    return measures.locality(anchored.gram_positions(_queries(spark, d), SPEC, ["query_id"]), bits=cachesim.LINE_BITS)


def _sweep(spark, d, specs, query=None):
    """One row a spec: rate, locality of the probes, bits set."""
    rows = reads(spark, d).cache()
    q = workload.poison(rows, K).select("query_id", "seq").cache()
    truth = baselines.exact_mt(rows, q, K, "dna").cache()
    each = [spec for _, spec in specs]
    if not filters.fit(each):
        raise ValueError("a sweep is over small filters that the kernel knows")
    rate = measures.fpr_mt_each(filters.contains_each(filters.build_each(rows, each), q, each), truth, len(each))
    met = measures.probe_localities(q, each, [PAGE_BITS, cachesim.LINE_BITS])
    of = lambda size, c: F.max(F.when(F.col("block") == size, F.col(c)))
    met = met.groupBy("number").agg(of(cachesim.LINE_BITS, "blocks_per_access").alias("lines_per_probe"), of(PAGE_BITS, "blocks_per_access").alias("pages_per_probe"), of(PAGE_BITS, "changes_per_access").alias("page_changes"))
    told = F.array(*[F.struct(F.lit(name).alias("hash"), F.lit(spec.m).cast("long").alias("m"), F.lit(spec.eta).alias("eta"), F.lit(spec.t).alias("t"), F.lit(spec.L).alias("L")) for name, spec in specs])
    out = rate.join(met, "number", "left").withColumn("s", F.element_at(told, F.col("number") + 1))
    return out.select("s.*", "negatives", "false_hits", "fpr", "lines_per_probe", "pages_per_probe", "page_changes")


@register("fpr_by_hash_table")
def fpr_by_hash_table(spark, d):
    """Three hashes on three sizes: which wins on accuracy and which on locality."""
    return _sweep(spark, d, [(h, FAST.with_(hash=h, m=m)) for m in (1 << 22, 1 << 23, 1 << 24) for h in ("sketch", "uniform", "anchored")])


@register("sweep_m")
def sweep_m(spark, d):
    return _sweep(spark, d, [(h, FAST.with_(hash=h, m=m)) for m in (1 << 21, 1 << 23, 1 << 25) for h in ("uniform", "anchored")])


@register("sweep_eta")
def sweep_eta(spark, d):
    return _sweep(spark, d, [("anchored", FAST.with_(eta=e)) for e in (1, 2, 4, 8)])


@register("sweep_t")
def sweep_t(spark, d):
    return _sweep(spark, d, [("anchored", FAST.with_(t=t)) for t in (4, 8, 12, 16, 20, 31)])


@register("sweep_L")
def sweep_L(spark, d):
    return _sweep(spark, d, [("anchored", FAST.with_(L=L, m=1 << 24)) for L in (1 << 6, 1 << 9, 1 << 12, 1 << 15, 1 << 17)])


@register("cache_miss_rates")
def cache_miss_rates(spark, d):
    """Simulated two-level cache over each file's probes, for the three hashes: 32 KB and 512 KB."""
    p = poisoned(spark, d).select(F.col("origin_file").alias("file_id"), "query_id", "seq")
    out = None
    for h in ("sketch", "uniform", "anchored"):
        got = cachesim.gram_miss_rates(p, FAST.with_(hash=h, m=1 << 25), "file_id", ["query_id"], (512, 8192)).withColumn("hash", F.lit(h))
        out = got if out is None else out.unionByName(got)
    return out.groupBy("hash").agg(F.sum("accesses").alias("accesses"), (F.sum("l1_misses") / F.sum("accesses")).alias("l1_rate"), (F.sum("last_misses") / F.sum("accesses")).alias("last_rate"))


@register("assumption_table", "WITH " + SEQS + ",\n" + FAR.replace("[1, 2, 3, 4]", "range(1, 17)") + ", z AS (SELECT source AS file_id, count(*)::BIGINT AS pairs, avg((NOT list_has_any(x, y))::INTEGER) AS zero_rate FROM f4 GROUP BY source), n AS (SELECT source AS file_id, sum(len(s))::BIGINT AS symbols FROM seqs GROUP BY source) SELECT file_id, pairs, zero_rate, symbols FROM z JOIN n USING (file_id)")
def assumption_table(spark, d):
    """Files of different size: share of far pairs without a common subgram."""
    rows = docs(spark, d, "source")
    sizes = rows.groupBy("file_id").agg(F.sum(F.length("seq")).cast("long").alias("symbols"))
    return measures.far_pair_zero_rate(rows, K, T, per_seq=16).join(sizes, "file_id")


FORMULA_POINTS = [(m, e) for m in (1 << 22, 1 << 26, 1 << 30) for e in (1, 2, 4)]
FORMULA_SQL = "WITH " + SEQS + f", f AS (SELECT source AS file_id, sum(greatest(len(s) - {K - 1}, 0))::BIGINT AS n FROM seqs GROUP BY source) SELECT file_id, "
POINTS_SQL = " FROM f CROSS JOIN (VALUES " + ", ".join(f"({m}::BIGINT, {e}::INTEGER)" for m, e in FORMULA_POINTS) + ") v(m, eta)"


def _file_grams(spark, d):
    """(file_id, n): the grams of every file of documents."""
    n = F.greatest(F.length("seq") - (K - 1), F.lit(0))
    return docs(spark, d, "source").groupBy("file_id").agg(F.sum(n).cast("long").alias("n"))


def _formula_points(spark, d):
    """(file_id, n, m, eta): the files at all sizes and numbers of functions."""
    points = F.explode(F.array(*[F.struct(F.lit(m).cast("long").alias("m"), F.lit(e).alias("eta")) for m, e in FORMULA_POINTS]))
    return _file_grams(spark, d).select("file_id", "n", points.alias("p")).select("file_id", "p.m", "n", "p.eta")


@register("fpr_formula_table", FORMULA_SQL + "m, n, eta, pow(1 - exp(-eta * n / m::DOUBLE), eta) AS fpr" + POINTS_SQL)
def fpr_formula_table(spark, d):
    """The closed form of the uniform rate for the files of documents, by their grams."""
    rate = F.udf(lambda m, n, e: theory.fpr_uniform(m, n, e), "double")
    return _formula_points(spark, d).withColumn("fpr", rate("m", "n", "eta"))


@register("bound_table", FORMULA_SQL + "m, n, eta, least(1, pow(256 * (1 / 4096.0 + eta / m::DOUBLE) + 2 * (1 - exp(-eta * n / (2 * m::DOUBLE))), eta)) AS bound, pow(256 / 4096.0, eta) AS limit_" + POINTS_SQL)
def bound_table(spark, d):
    """The bound of the anchored rate, and what it tends to, for the files of documents."""
    bound = F.udf(lambda m, n, e: theory.fpr_anchored_bound(m, n, e, 4096, 31, 256), "double")
    limit = F.udf(lambda e: theory.fpr_anchored_limit(e, 4096, 256), "double")
    return _formula_points(spark, d).withColumn("bound", bound("m", "n", "eta")).withColumn("limit_", limit("eta"))


@register("hash_cost_table", "WITH " + SEQS + f""", f AS (SELECT source AS file_id, sum(greatest(len(s) - {K - 1}, 0))::BIGINT AS n FROM seqs GROUP BY source),
p AS (SELECT t, eta, {K} - t + 1 AS w, ceil(log2({K} - t + 1)) AS deep FROM (VALUES (12), (16), (20)) a(t), (VALUES (1), (4)) b(eta)),
r AS (SELECT t, eta, 'uniform' AS road, eta AS hashes, 0 AS compares FROM p UNION ALL SELECT t, eta, 'naive', eta * (w + 1), eta * (w - 1) FROM p
UNION ALL SELECT t, eta, 'rolling', 2 * eta, eta * deep FROM p UNION ALL SELECT t, eta, 'one_permutation', eta + 1, eta * deep FROM p)
SELECT file_id, t::INTEGER AS t, eta::INTEGER AS eta, road, hashes::DOUBLE AS hashes, compares::DOUBLE AS compares, n * hashes::DOUBLE AS all_hashes, n * compares::DOUBLE AS all_compares FROM f CROSS JOIN r""")
def hash_cost_table(spark, d):
    """Hashes and comparisons a gram by each road, and for all grams of every file of documents."""
    roads = [(t, e, road, float(c["hashes"]), float(c["compares"])) for t in (12, 16, 20) for e in (1, 4) for road, c in theory.hash_ops(K, t, e).items()]
    each = F.explode(F.array(*[F.struct(*[F.lit(v).alias(c) for c, v in zip(("t", "eta", "road", "hashes", "compares"), r)]) for r in roads])).alias("r")
    rows = _file_grams(spark, d).select("file_id", "n", each).select("file_id", "n", "r.*")
    return rows.select("file_id", "t", "eta", "road", "hashes", "compares", (F.col("n") * F.col("hashes")).alias("all_hashes"), (F.col("n") * F.col("compares")).alias("all_compares"))


# ---------------------------------------------------------------- other sequences

@register("benchmark_contamination", "WITH " + GRAMS + f""", {BENCH_SEQS}, qg AS (SELECT item_id, substr(s, p, {K}) AS g FROM (SELECT *, {_at(K)} AS p FROM (SELECT item_id, q AS s FROM bs))),
dq AS (SELECT DISTINCT item_id, g FROM qg), need AS (SELECT item_id, count(*)::BIGINT AS n_grams FROM dq GROUP BY 1), have AS (SELECT item_id, doc_id, count(*)::BIGINT AS n_hit FROM dq JOIN (SELECT DISTINCT doc_id, g FROM grams) USING (g) GROUP BY ALL)
SELECT item_id, doc_id, n_grams, n_hit FROM have JOIN need USING (item_id) WHERE n_hit >= 0.5 * n_grams""")
def benchmark_contamination(spark, d):
    """Documents that hold at least half of the grams of a benchmark item, exactly."""
    items = table(spark, d, "benchmark").select("item_id", views.dna(F.col("text")).alias("seq"))
    want = grams.gram_set(items, ["item_id"], "seq", K)
    need = want.groupBy("item_id").agg(F.count(F.lit(1)).alias("n_grams"))
    known = grams.explode_grams(reads(spark, d), "seq", K).select(F.col("seq_id").alias("doc_id"), "gram")
    have = known.join(want, "gram").distinct().groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("n_hit"))
    return have.join(need, "item_id").where("n_hit >= 0.5 * n_grams").select("item_id", "doc_id", "n_grams", "n_hit")


@register("conversation_token_search")
def conversation_token_search(spark, d):
    """Turns of assistants looked up, by 5-token grams under anchored hashing, among the turns of users."""
    t = views.token_sequences(table(spark, d, "conversations"), keys=("conv_id", "turn", "role"))
    g = t.select("conv_id", "turn", "role", F.posexplode(grams.token_grams(F.col("tokens"), 5)).alias("pos", "gram"))
    phi = F.array_min(F.transform(F.split("gram", "\x1f"), lambda w: sketch.raw_hash(w, 1, "xxhash64")))
    placed = g.select("conv_id", "turn", "role", "pos", anchored.position(F.col("gram"), phi, 1 << 22, 1024).alias("bit"))
    index = pages.from_positions(placed.where("role = 'user'").select(F.lit(0).alias("rep"), "bit"), ["rep"])
    asked = placed.where("role != 'user'").groupBy("conv_id", "turn", pages.page_of(F.col("bit")).alias("page_no")).agg(F.collect_set(pages.offset_of(F.col("bit"))).alias("o"))
    met = asked.join(F.broadcast(index.select("page_no", "bits")), "page_no", "left")  # at most 128 pages of 4 KB
    return met.groupBy("conv_id", "turn").agg(F.sum(F.size("o")).alias("n_bits"), F.sum(F.coalesce(F.size(F.filter("o", lambda x: pages.bit_at(F.col("bits"), x))), F.lit(0))).alias("n_set"))


@register("log_pattern_search", """WITH l AS (SELECT user_id, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS s FROM events GROUP BY user_id),
g AS (SELECT DISTINCT user_id, substr(s, p, 8) AS g FROM (SELECT *, unnest(range(1, greatest(len(s) - 7, 0) + 1)) AS p FROM l)),
q AS (SELECT DISTINCT substr(s, p, 10) AS pattern FROM (SELECT *, unnest(range(1, greatest(len(s) - 9, 0) + 1)) AS p FROM l)), qg AS (SELECT DISTINCT pattern, substr(pattern, p, 8) AS g FROM (SELECT *, unnest(range(1, 4)) AS p FROM q)), need AS (SELECT pattern, count(*) AS n FROM qg GROUP BY 1)
SELECT pattern, count(*)::BIGINT AS n_users FROM (SELECT pattern, user_id FROM qg JOIN g USING (g) JOIN need USING (pattern) GROUP BY pattern, user_id, n HAVING count(*) = n) GROUP BY pattern""")
def log_pattern_search(spark, d):
    """For every run of ten events that occurs: users whose log holds all its grams of eight, exactly."""
    logs = views.log_sequences(table(spark, d, "events"))
    known = grams.gram_set(logs, ["seq_id"], "seq", 8)
    patterns = grams.gram_set(logs, [], "seq", 10).select(F.col("gram").alias("pattern"))
    want = grams.gram_set(patterns, ["pattern"], "pattern", 8)
    need = want.groupBy("pattern").agg(F.count(F.lit(1)).alias("n"))
    have = want.join(known, "gram").groupBy("pattern", "seq_id").agg(F.count(F.lit(1)).alias("h"))
    return have.join(need, "pattern").where("h = n").groupBy("pattern").agg(F.count(F.lit(1)).alias("n_users"))


@register("log_filter_anchored")
def log_filter_anchored(spark, d):
    """The same logs in an anchored filter over any alphabet: every user's own log is found."""
    spec = IndexSpec(k=8, t=4, eta=2, m=1 << 18, L=1024, alphabet="any", backend="sql")
    logs = views.log_sequences(table(spark, d, "events"))
    return filters.contains(filters.build(logs, spec, combine="bits"), logs.select(F.col("seq_id").alias("query_id"), "seq"), spec)


@register("vector_symbol_search")
def vector_symbol_search(spark, d):
    """Quantised vectors as strings: coverage of each vector by the filter of the vectors with label 0."""
    spec = IndexSpec(k=8, t=4, eta=2, m=1 << 20, L=1024, alphabet="any", backend="sql")
    v = table(spark, d, "embeddings")
    index = filters.build(views.vector_sequences(v.where("label = 0")), spec, combine="bits")
    return filters.coverage(index, views.vector_sequences(v).select(F.col("seq_id").alias("query_id"), "seq"), spec)


@register("native_text_filter")
def native_text_filter(spark, d):
    """Benchmark items, as they are, in the anchored filter of the documents' own texts."""
    spec = IndexSpec(k=31, t=16, eta=2, m=1 << 24, L=4096, alphabet="any", backend="sql")
    rows = views.to_reads(views.native_sequences(table(spark, d, "documents").repartition(F.col("doc_id"))), K)
    items = table(spark, d, "benchmark").select(F.col("item_id").alias("query_id"), F.col("text").alias("seq"))
    return filters.coverage(filters.build(rows, spec, combine="bits"), items, spec)


def _vector_pairs(spark, d):
    """The stated query set, vectors whose number is divisible by 100, against all others."""
    v = table(spark, d, "embeddings").select("vec_id", "label", "embedding", sketch.sign_projection(F.col("embedding"), PLANES[:4]).alias("phi"), F.lit(1).alias("one"))
    v = v.withColumn("pos", anchored.position(F.col("vec_id"), F.col("phi"), 1 << 20, 1024))
    a = v.where("vec_id % 100 = 0").select(*[F.col(c).alias(f"a_{c}") for c in v.columns])
    pairs = v.join(F.broadcast(a), F.col("a_vec_id") != F.col("vec_id"))
    dot = F.aggregate(F.zip_with("a_embedding", "embedding", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda x, y: x + y)
    norm = lambda c: F.sqrt(F.aggregate(F.transform(c, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda x, y: x + y))
    return pairs.withColumn("distance", F.acos(F.least(F.lit(1.0), F.greatest(F.lit(-1.0), dot / (norm("a_embedding") * norm("embedding"))))))


@register("lsh_sensitivity")
def lsh_sensitivity(spark, d):
    """Collisions of the angular sketch, and closeness of anchored positions, by band of angle."""
    p = _vector_pairs(spark, d)
    a = measures.sensitivity(p, F.col("distance"), F.col("a_phi") == F.col("phi"), 8, 3.1416)
    b = measures.preservation(p, F.col("distance"), F.col("a_pos"), F.col("pos"), 1024, 8, 3.1416).drop("pairs")
    return a.join(b, "band")


@register("anchored_count_sketch", """SELECT event_type, count(*)::BIGINT AS n_true FROM events GROUP BY event_type""")
def anchored_count_sketch(spark, d):
    """Counts of event types from a count-min table whose cells are anchored positions; exact here, as no cells meet."""
    e = table(spark, d, "events").select("event_type")
    cell = lambda r: anchored.position(F.col("event_type"), sketch.minwise(grams.gram_array(F.col("event_type"), 2), r), 1 << 16, 256, r)
    rows = e.select("event_type", F.explode(F.array(*[F.struct(F.lit(r).alias("r"), cell(r).alias("c")) for r in (1, 2, 3)])).alias("x")).select("event_type", "x.r", "x.c")
    counted = rows.groupBy("r", "c").agg(F.count(F.lit(1)).alias("n"))
    return rows.distinct().join(counted, ["r", "c"]).groupBy("event_type").agg(F.min("n").alias("n_true"))


def flagship(spark, d):
    """Poisoned pieces of the documents, their answers by the anchored filter, and the truth."""
    q = poisoned(spark, d)
    got = filters.contains(filters.build(reads(spark, d), FAST), q.select("query_id", "seq"), FAST)
    truth = baselines.exact_mt(reads(spark, d), q.select("query_id", "seq"), K, "dna").withColumnRenamed("hit", "is_member")
    return got.join(truth, "query_id").select("query_id", "hit", "is_member")


register("flagship_membership")(flagship)

__all__ = ["QUERIES", "SQL", "PAGE_BITS", "flagship"]
