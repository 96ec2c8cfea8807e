"""Relational and function queries around the methods: one SQL text for Spark and DuckDB where both read it alike.

Tables stand in braces. What the two engines write differently has a text for each.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import baselines, evaluate, model, segment
from ..shipping import ship
from ..sources import corpus
from ..sources.store import kept
from ..streaming import streams
from . import oracles, workloads

BOTH = {
    "r01_pricing_summary": """SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS avg_disc, count(*) AS n
        FROM {lineitem} WHERE l_shipdate <= TIMESTAMP '1998-09-02 00:00:00' GROUP BY l_returnflag, l_linestatus""",
    "r02_revenue_by_nation": """SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM {customer} JOIN {orders} ON c_custkey = o_custkey JOIN {lineitem} ON l_orderkey = o_orderkey
        JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey WHERE r_name IN ('ASIA', 'EUROPE') GROUP BY n_name""",
    "r03_semi_orders": """SELECT o_orderpriority, count(*) AS n FROM {orders} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey AND l_quantity > 45) GROUP BY o_orderpriority""",
    "r04_anti_customers": """SELECT c_custkey, c_name FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')""",
    "r06_range_join": """SELECT b.lo, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM (SELECT 0.0 AS lo, 0.02 AS hi UNION ALL SELECT 0.02, 0.05 UNION ALL SELECT 0.05, 1.0) b JOIN {lineitem} ON l_discount >= b.lo AND l_discount < b.hi GROUP BY b.lo""",
    "r09_cube_lang_source": """SELECT coalesce(lang, '*') AS lang, coalesce(source, '*') AS source, count(*) AS docs, sum(n_chars) AS chars FROM {documents} GROUP BY CUBE (lang, source)""",
    "r11_grouping_sets": """SELECT coalesce(lang, '*') AS lang, coalesce(source, '*') AS source, count(*) AS docs FROM {documents} GROUP BY GROUPING SETS ((lang), (source), ())""",
    "r16_except_all": """SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey FROM {supplier}""",
    "r18_date_fns": """SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, max(year(o_orderdate)) AS y, min(month(o_orderdate)) AS m FROM {orders} GROUP BY date_trunc('month', o_orderdate)""",
    "r19_math_fns": """SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(exp(p_size / 50.0), 6) AS e, round(sqrt(p_retailprice), 6) AS r, round(power(p_size, 1.5), 6) AS p, round(log2(p_size + 1), 6) AS b,
        greatest(p_size, 25) AS g, least(p_size, 25) AS s FROM {part}""",
    "r34_labels_join": """SELECT d.lang, l.quality, l.toxic, count(*) AS n, sum(d.n_chars) AS chars FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id GROUP BY d.lang, l.quality, l.toxic""",
    "r35_priority_check": """SELECT o_orderpriority, sum(CASE WHEN o_totalprice BETWEEN 50000 AND 150000 THEN 1 ELSE 0 END) AS middle, count(*) AS n FROM {orders} WHERE o_orderstatus <> 'P' AND o_orderpriority LIKE '%-%' GROUP BY o_orderpriority""",
    "r36_top_customers": """SELECT c_custkey, round(sum(o_totalprice), 2) AS spent FROM {customer} JOIN {orders} ON c_custkey = o_custkey GROUP BY c_custkey ORDER BY sum(o_totalprice) DESC, c_custkey LIMIT 20""",
}
#: Spark's text, then DuckDB's.
APART = {
    "r17_string_fns": (
        """SELECT c_custkey, length(c_name) AS n, substring(c_name, 1, 4) AS head, left(c_name, 3) AS l, right(c_name, 3) AS r, reverse(c_name) AS rev, translate(c_name, '#0', '-o') AS t, trim(lower(c_name)) AS low, concat_ws('/', c_name, c_mktsegment) AS both,
        levenshtein(c_mktsegment, 'BUILDING') AS d, ascii(c_name) AS a, chr(65 + c_nationkey) AS c, split(c_name, '#')[0] AS part FROM {customer}""",
        """SELECT c_custkey, length(c_name) AS n, substring(c_name, 1, 4) AS head, left(c_name, 3) AS l, right(c_name, 3) AS r, reverse(c_name) AS rev, translate(c_name, '#0', '-o') AS t, trim(lower(c_name)) AS low, concat_ws('/', c_name, c_mktsegment) AS both,
        levenshtein(c_mktsegment, 'BUILDING') AS d, ascii(c_name) AS a, chr(65 + c_nationkey) AS c, string_split(c_name, '#')[1] AS part FROM {customer}""",
    ),
    "r21_json_props": (
        """SELECT k, count(*) AS n FROM (SELECT explode(json_object_keys(props)) AS k FROM {events} WHERE props IS NOT NULL) GROUP BY k""",
        """SELECT k, count(*) AS n FROM (SELECT unnest(json_keys(props)) AS k FROM {events} WHERE props IS NOT NULL) GROUP BY k""",
    ),
    "r25_tumbling": (
        """SELECT date_trunc('hour', ts) AS at, event_type, count(*) AS n, round(sum(value), 4) AS total FROM {events} GROUP BY date_trunc('hour', ts), event_type""",
        """SELECT date_trunc('hour', ts) AS at, event_type, count(*) AS n, round(sum(value), 4) AS total FROM {events} GROUP BY ALL""",
    ),
}


def _sql(text: str):
    names = [n for n in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations") if f"{{{n}}}" in text]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(text, **{n: corpus.table(spark, sf_dir, n) for n in names})

    return run


def _plain(text: str) -> str:
    return text.replace("{", "").replace("}", "")


def r05_full_outer_bags(spark, sf_dir):
    """Symbol bags of two languages side by side."""
    one = model.count_grams(corpus.all_lines(spark, sf_dir), 1)
    pick = lambda g: one.where(F.col("lang") == g).select("gram", F.col("cnt").alias(g))
    return pick("en").join(pick("de"), "gram", "full_outer")


def r07_asof_events(spark, sf_dir):
    """For each order the latest event before it of the user with the customer's number: both sides in one sorted stream, the last event carried along."""
    orders = corpus.table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("who"), F.col("o_orderdate").alias("at"), F.lit(1).alias("side"), F.col("o_orderkey").alias("key"))
    events = corpus.table(spark, sf_dir, "events").select(F.col("user_id").alias("who"), F.col("ts").alias("at"), F.lit(0).alias("side"), F.col("event_id").alias("key"))
    # Events come before orders of the same time.
    before = Window.partitionBy("who").orderBy("at", "side", "key").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("side") == 0, F.col("key")), ignorenulls=True).over(before)
    return orders.unionByName(events).withColumn("event_id", last).where("side = 1").select(F.col("key").alias("o_orderkey"), "event_id")


def r08_interval_events(spark, sf_dir):
    """For each event how many of the same user follow within an hour. An event is counted among those of its own hour and of the hour before, so what meets is a user's two hours, not all that a user ever did; there a range frame counts."""
    hour = 3_600_000_000
    ev = corpus.table(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    own = F.floor(F.col("at") / hour)
    each = ev.withColumn("hour", F.explode(F.array(own, own - 1)))
    near = Window.partitionBy("user_id", "hour").orderBy("at").rangeBetween(1, hour)
    return each.withColumn("later", F.count("event_id").over(near)).where(F.col("hour") == own).select("event_id", "later")


def r10_rollup_model_size(spark, sf_dir):
    """Counts held by the model by language, rank and part, with sums on each level."""
    grams = kept(workloads.grams_of(spark, sf_dir, 3))
    parts = grams.where("n < 3").select("lang", "n", F.lit("v").alias("part"), "cnt").unionByName(model.edges(grams).select("lang", "n", F.col("dir").alias("part"), "cnt"))
    rolled = parts.rollup("lang", "n", "part").agg(F.count("*").alias("params"), F.sum("cnt").alias("weight"))
    return rolled.select(F.coalesce("lang", F.lit("*")).alias("lang"), F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("part", F.lit("*")).alias("part"), "params", "weight")


def r12_topk_grams(spark, sf_dir):
    """The ten most frequent grams of each language and rank."""
    order = Window.partitionBy("lang", "n").orderBy(F.desc("cnt"), "gram")
    return workloads.grams_of(spark, sf_dir, 3).withColumn("k", F.row_number().over(order)).where("k <= 10")


def r13_window_frames(spark, sf_dir):
    """A moving mean over five gaps of the forward freedom of each benchmark item."""
    p = segment.base_profile(corpus.benchmark(spark, sf_dir), kept(workloads.grams_of(spark, sf_dir, 2)), "tf", [1]).where("dir = 'f'")
    frame = Window.partitionBy("stmt_id").orderBy("gap").rowsBetween(-2, 2)
    return p.select("stmt_id", "gap", F.round(F.avg("v").over(frame), 6).alias("mean"), F.first("v").over(frame).alias("first"), F.last("v").over(frame).alias("last"))


def r14_ntile_halves(spark, sf_dir):
    """Halves, quartiles and ranks of documents by length, within each language and source."""
    by = Window.partitionBy("lang", "source").orderBy("n_chars", "doc_id")
    docs = corpus.table(spark, sf_dir, "documents")
    rank = Window.partitionBy("lang", "source").orderBy("n_chars")
    return docs.select("doc_id", F.ntile(2).over(by).alias("half"), F.ntile(4).over(by).alias("quarter"), F.rank().over(rank).alias("rank"), F.dense_rank().over(rank).alias("dense"))


def r15_set_ops(spark, sf_dir):
    """Symbols that English shares with German, and those that only one has."""
    one = model.count_grams(corpus.all_lines(spark, sf_dir), 1)
    of = lambda g: one.where(F.col("lang") == g).select("gram")
    tag = lambda df, t: df.withColumn("part", F.lit(t))
    return tag(of("en").intersect(of("de")), "both").unionByName(tag(of("en").subtract(of("de")), "en")).unionByName(tag(of("de").subtract(of("en")), "de")).unionByName(tag(of("en").union(of("de")).distinct(), "any"))


def r20_array_map_fns(spark, sf_dir):
    """Array and map functions over the symbols of benchmark items."""
    symbols = F.split("text", "")
    return corpus.table(spark, sf_dir, "benchmark").select(
        "item_id", F.size(symbols).alias("n"), F.size(F.filter(symbols, lambda x: x == " ")).alias("blanks"), F.array_join(F.slice(symbols, 1, 3), "-").alias("head"), F.size(F.array_distinct(symbols)).alias("kinds"),
        F.aggregate(symbols, F.lit(0), lambda a, x: a + F.length(x)).alias("total"), F.array_join(F.transform(F.sequence(F.lit(1), F.lit(3)), lambda i: F.element_at(symbols, i)), "").alias("first"),
        F.coalesce(F.element_at(F.map_from_entries(F.array(F.struct(F.lit("a"), F.lit(1)), F.struct(F.lit("b"), F.lit(2)))), "b"), F.lit(0)).alias("b"),
    )


def r22_pivot_lang(spark, sf_dir):
    docs = corpus.table(spark, sf_dir, "documents")
    return docs.groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


def r23_unpivot(spark, sf_dir):
    return corpus.table(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value")


def r24_distinct_exact_approx(spark, sf_dir):
    """Exact distinct words of each language; the sketch's count has to be near."""
    words = corpus.table(spark, sf_dir, "documents").select("lang", F.explode(F.filter(F.split("text", "[ \n]+"), lambda x: x != "")).alias("w"))
    out = words.groupBy("lang").agg(F.countDistinct("w").alias("exact"), F.approx_count_distinct("w", 0.02).alias("a"))
    return out.select("lang", "exact", (F.abs(F.col("a") / F.col("exact") - 1) < 0.1).alias("near"))


def r26_sliding(spark, sf_dir):
    """Events in windows of two hours that begin every hour."""
    ev = corpus.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return ev.groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("n")).select(F.unix_timestamp("window.start").alias("begins"), "n")


def r27_session(spark, sf_dir):
    """Sessions of a user's events without a gap of an hour or more."""
    ev = corpus.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return ev.groupBy("user_id", F.session_window("ts", "1 hour")).agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("session_window.start").alias("begins"), "n")


def r28_sketch_freedom(spark, sf_dir):
    """Forward freedom at rank 2, exact and by sketches; the sketch has to be near."""
    sketch = model.freedom_sketch(corpus.all_lines(spark, sf_dir), 2).withColumnRenamed("tf_f", "a")
    exact = model.freedom(model.symbol_edges(workloads.grams_of(spark, sf_dir, 3).where("n = 3"), "f"))
    both = exact.join(sketch, list(model.KEYS), "full_outer")
    return both.select(*model.KEYS, "tf", (F.abs(F.col("a") - F.col("tf")) <= 1 + 0.05 * F.col("tf")).alias("near"))


def r29_udf_segment(spark, sf_dir):
    """Tokens by the registered SQL function, which has to agree with the row engine."""
    grams = kept(workloads.grams_of(spark, sf_dir, 2))
    udfs.register(spark, grams, workloads.SPACED)
    st = corpus.corpus_statements(spark, sf_dir)
    return spark.sql("SELECT lang, stmt_id, pos + 1 AS tok_no, col AS token FROM (SELECT lang, stmt_id, posexplode(segment_text(lang, text)) FROM {st})", st=st)


def r30_udtf_grams(spark, sf_dir):
    """Grams of benchmark items by the table function."""
    udfs.register_tables(spark)
    return spark.sql("SELECT item_id, g.place, g.gram FROM {b}, LATERAL text_grams(text, 2) g", b=corpus.table(spark, sf_dir, "benchmark"))


def r31_stream_counts(spark, sf_dir):
    """Gram counts by a stream over the documents' files; equal to the batch's."""
    return streams.run_counts(spark, f"{sf_dir}/documents.parquet", 2)


def r32_stream_late_rows(spark, sf_dir):
    """Hourly counts of a stream of events in append mode. The events come in two files, then a third repeats those of the first quarter of the time; its rows are later than the watermark and are dropped. Windows that the watermark has not passed are not given yet."""
    ev = corpus.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    at = F.unix_micros("ts")
    first, last = ev.agg(F.min(at), F.max(at)).first()
    half, quarter = first + (last - first) // 2, first + (last - first) // 4
    return streams.run_windows(spark, [ev.where(at < half), ev.where(at >= half), ev.where(at < quarter)])


def r33_part_name_segments(spark, sf_dir):
    """Part names without their blank, segmented by freedom learned from them, and how many of the true breaks are found."""
    names = corpus.table(spark, sf_dir, "part").select(F.lit("part").alias("lang"), F.col("p_name").alias("stmt_id")).distinct()
    st = kept(names.select("lang", "stmt_id", F.translate("stmt_id", " ", "").alias("text"), F.length(F.substring_index("stmt_id", " ", 1)).alias("gap")).where("length(text) >= 2"))
    grams = kept(model.count_grams(st.select("lang", F.col("text").alias("line")), 3))
    cuts = segment.run(st, grams, workloads.EVENTS).where("start > 1").select("lang", "stmt_id", (F.col("start") - 1).alias("gap"))
    return evaluate.boundary_f1(cuts, st.where("gap < length(text)").select("lang", "stmt_id", "gap"))


def r37_sessions(spark, sf_dir):
    """Each user's sessions, as strings of events cut by freedom: tokens of a session stay inside it."""
    return streams.session_tokens(corpus.table(spark, sf_dir, "events"), workloads.EVENTS)


def r38_json_lines(spark, sf_dir):
    """Three fields of JSON records, each a line of its own."""
    records = corpus.table(spark, sf_dir, "conversations").select("conv_id", "turn", F.to_json(F.struct(F.col("role").alias("title"), F.col("text").alias("content"), F.col("conv_id").cast("string").alias("desc"))).alias("j"))
    return corpus.json_lines(records, "j", ["title", "desc", "content"], "conv_id", "turn")


def r39_udtf_tokens(spark, sf_dir):
    """Benchmark items segmented by the freedom of their own symbols, by the table function."""
    udfs.register_tables(spark)
    return spark.sql("SELECT item_id, t.tok_no, t.start, t.token FROM {b}, LATERAL text_tokens(text, 0.4) t", b=corpus.table(spark, sf_dir, "benchmark"))


def r40_udaf_bag_f1(spark, sf_dir):
    """F1 of these tokens against the reference tokens of each item, by the registered aggregate."""
    udfs.register_measures(spark)
    items = corpus.table(spark, sf_dir, "benchmark").select(F.lit("en").alias("lang"), F.col("item_id").alias("stmt_id"), "text")
    hyp = evaluate.solid(r39_udtf_tokens(spark, sf_dir)).select("item_id", F.col("token").alias("hyp"), F.lit(None).cast("string").alias("ref"))
    ref = baselines.reference_tokens(items).select(F.col("stmt_id").alias("item_id"), F.lit(None).cast("string").alias("hyp"), F.col("token").alias("ref"))
    return spark.sql("SELECT item_id, round(bag_f1(hyp, ref), 6) AS f1 FROM {t} GROUP BY item_id", t=hyp.unionByName(ref))


def _shipped(f):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    return run


QUERIES = {k: _sql(v) for k, v in BOTH.items()} | {k: _sql(v[0]) for k, v in APART.items()} | {k: _shipped(f) for k, f in sorted(globals().items()) if k[:1] == "r" and k[1:3].isdigit()}

_o = oracles
#: Each item is a corpus of its own.
OWN_TOKENS = _o.query(
    ["stmts AS MATERIALIZED (SELECT CAST(item_id AS VARCHAR) AS lang, item_id AS stmt_id, text FROM benchmark)", "lines AS (SELECT lang, text AS line FROM stmts)", *_o.model(2), _o.gaps([1]), _o.base("tf", 0.0)],
    f", toks AS ({_o.tokens(segment.Config(theta=0.0))}), placed AS (SELECT *, sum(length(token)) OVER (PARTITION BY stmt_id ORDER BY tok_no) - length(token) + 1 AS a FROM toks)",
)
ORACLES = (
    {k: _plain(v) for k, v in BOTH.items()}
    | {k: _plain(v[1]) for k, v in APART.items()}
    | {
        "r05_full_outer_bags": _o.query([*_o.WHOLE, _o.grams(1)], "SELECT * FROM (SELECT gram, cnt AS en FROM grams WHERE lang = 'en') FULL OUTER JOIN (SELECT gram, cnt AS de FROM grams WHERE lang = 'de') USING (gram)"),
        "r07_asof_events": """SELECT o_orderkey, (SELECT arg_max(event_id, (ts, event_id)) FROM events WHERE user_id = o_custkey AND ts <= o_orderdate) AS event_id FROM orders""",
        "r10_rollup_model_size": _o.query([*_o.WHOLE, _o.grams(3), _o.edges()], """SELECT coalesce(lang, '*') AS lang, coalesce(n, 0) AS n, coalesce(part, '*') AS part, count(*) AS params, CAST(sum(cnt) AS BIGINT) AS weight
            FROM (SELECT lang, n, 'v' AS part, cnt FROM grams WHERE n < 3 UNION ALL SELECT lang, n, dir, cnt FROM edges) GROUP BY ROLLUP (lang, n, part)"""),
        "r12_topk_grams": _o.query([*_o.WHOLE, _o.grams(3)], "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY lang, n ORDER BY cnt DESC, gram) AS k FROM grams) WHERE k <= 10"),
        "r13_window_frames": _o.query(_o.TF1, """SELECT stmt_id, gap, round(avg(v) OVER w, 6) AS mean, first_value(v) OVER w AS "first", last_value(v) OVER w AS "last" FROM prof WHERE dir = 'f'
            WINDOW w AS (PARTITION BY stmt_id ORDER BY gap ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING)"""),
        "r08_interval_events": "SELECT a.event_id, count(b.event_id) AS later FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.event_id",
        "r14_ntile_halves": """SELECT doc_id, ntile(2) OVER w AS half, ntile(4) OVER w AS quarter, rank() OVER r AS "rank", dense_rank() OVER r AS dense FROM documents
            WINDOW w AS (PARTITION BY lang, source ORDER BY n_chars, doc_id), r AS (PARTITION BY lang, source ORDER BY n_chars)""",
        "r15_set_ops": _o.query([*_o.WHOLE, _o.grams(1), "en AS (SELECT gram FROM grams WHERE lang = 'en')", "de AS (SELECT gram FROM grams WHERE lang = 'de')"], """SELECT gram, 'both' AS part FROM (SELECT * FROM en INTERSECT SELECT * FROM de)
            UNION ALL SELECT gram, 'en' FROM (SELECT * FROM en EXCEPT SELECT * FROM de) UNION ALL SELECT gram, 'de' FROM (SELECT * FROM de EXCEPT SELECT * FROM en) UNION ALL SELECT gram, 'any' FROM (SELECT * FROM en UNION SELECT * FROM de)"""),
        "r20_array_map_fns": """SELECT item_id, length(text) AS n, CAST(len(list_filter(string_split(text, ''), lambda x: x = ' ')) AS INTEGER) AS blanks, array_to_string(list_slice(string_split(text, ''), 1, 3), '-') AS head,
            CAST(len(list_distinct(string_split(text, ''))) AS INTEGER) AS kinds, length(text) AS total, substr(text, 1, 3) AS "first", 2 AS b FROM benchmark""",
        "r22_pivot_lang": "SELECT source, " + ", ".join(f"count(*) FILTER (lang = '{g}') AS {g}" for g in ("de", "en", "es", "fr")) + " FROM documents GROUP BY source",
        "r23_unpivot": "SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels",
        "r24_distinct_exact_approx": r"""SELECT lang, count(DISTINCT w) AS exact, true AS near FROM (SELECT lang, unnest(regexp_split_to_array(text, '[ \n]+')) AS w FROM documents) WHERE w <> '' GROUP BY lang""",
        "r26_sliding": """SELECT CAST(epoch(h) AS BIGINT) AS begins, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY h""",
        "r27_session": """SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS begins, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
            SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""",
        "r29_udf_segment": _o.ORACLES["w15_tokens_tf_var"],
        "r30_udtf_grams": "SELECT item_id, CAST(i AS INTEGER) AS place, substr(text, i, 2) AS gram FROM (SELECT item_id, text, unnest(range(1, length(text))) AS i FROM benchmark)",
        "r31_stream_counts": _o.query(["docs AS (SELECT lang, text FROM documents)", _o.lines(), _o.grams(2)], "SELECT * FROM grams"),
        "r28_sketch_freedom": _o.query([*_o.WHOLE, _o.grams(3)], "SELECT lang, CAST(2 AS INTEGER) AS n, left(gram, 2) AS gram, count(*) AS tf, true AS near FROM grams WHERE n = 3 GROUP BY lang, left(gram, 2)"),
        "r32_stream_late_rows": """SELECT CAST(epoch(h) AS BIGINT) AS begins, event_type, count(*) AS n FROM (SELECT date_trunc('hour', ts) AS h, event_type FROM events)
            WHERE h + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL""",
        "r33_part_name_segments": _o.query(["stmts AS MATERIALIZED (SELECT DISTINCT 'part' AS lang, p_name AS stmt_id, replace(p_name, ' ', '') AS text FROM part WHERE length(replace(p_name, ' ', '')) >= 2)", "lines AS (SELECT lang, text AS line FROM stmts)", *_o.model(3), _o.gaps([2]), _o.base("tf", 0.0),
            f"hyp AS (SELECT lang, stmt_id, gap FROM ({_o.combined(_o.scaled(_o.offshoot('peak')))}) WHERE score > 0.5)", "ref AS (SELECT lang, stmt_id, length(split_part(stmt_id, ' ', 1)) AS gap FROM stmts WHERE length(split_part(stmt_id, ' ', 1)) < length(text))"],
            """SELECT lang, matched, hyp, ref, round(matched / hyp, 6) AS "precision", round(matched / ref, 6) AS recall, round(2 * matched / (hyp + ref), 6) AS f1 FROM (
            SELECT lang, count(*) FILTER (h IS NOT NULL AND r IS NOT NULL) AS matched, count(h) AS hyp, count(r) AS ref FROM (SELECT *, 1 AS h FROM hyp) FULL OUTER JOIN (SELECT *, 1 AS r FROM ref) USING (lang, stmt_id, gap) GROUP BY lang)"""),
        "r37_sessions": _o.query(["""cut AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))""",
            "numbered AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM cut)",
            "stmts AS MATERIALIZED (SELECT 'seq' AS lang, user_id || ':' || CAST(epoch(date_trunc('second', min(ts))) AS BIGINT) AS stmt_id, string_agg(left(event_type, 1), '' ORDER BY ts, event_id) AS text FROM numbered GROUP BY user_id, s)",
            "lines AS (SELECT lang, text AS line FROM stmts)", *_o.model(3), _o.gaps([2]), _o.base("tf", 0.0)], f"SELECT stmt_id, tok_no, token FROM ({_o.tokens(workloads.EVENTS)})"),
        "r39_udtf_tokens": f"{OWN_TOKENS} SELECT stmt_id AS item_id, tok_no, CAST(a AS INTEGER) AS start, token FROM placed",
        "r40_udaf_bag_f1": f"""{OWN_TOKENS}, ref AS ({_o.reference()}), h AS (SELECT stmt_id, token, count(*) AS h FROM placed WHERE trim(token) <> '' GROUP BY ALL), r AS (SELECT stmt_id, token, count(*) AS r FROM ref GROUP BY ALL)
            SELECT stmt_id AS item_id, round(2 * sum(least(coalesce(h, 0), coalesce(r, 0))) / (sum(coalesce(h, 0)) + sum(coalesce(r, 0))), 6) AS f1 FROM h FULL OUTER JOIN r USING (stmt_id, token) GROUP BY stmt_id""",
        "r38_json_lines": """SELECT conv_id, turn, field, line FROM (SELECT conv_id, turn, 'title' AS field, role AS line FROM conversations UNION ALL SELECT conv_id, turn, 'desc', CAST(conv_id AS VARCHAR) FROM conversations
            UNION ALL SELECT conv_id, turn, 'content', text FROM conversations) WHERE line <> ''""",
    }
)
