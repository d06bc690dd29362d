"""Registered queries of the operators around the search methods: sources, joins, aggregations, windows, functions, streams, UDFs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tauprobe.functions import registered
from tauprobe.session import scratch, table
from tauprobe.sources import workloads as wl
from tauprobe.streaming import events as ev

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

#: Buckets of the tables that are laid out by their join key.
BUCKETS = 16


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


def t(spark, sf, name):
    return table(spark, sf, name)


# ---- sources and sinks

@query("op_scan_pushdown_docs", "SELECT doc_id, lang, n_chars FROM documents WHERE lang IN ('de', 'fr') AND n_chars BETWEEN 500 AND 3000 AND source LIKE 'src1%' AND source IS NOT NULL")
def _(spark, sf):
    d = t(spark, sf, "documents")
    return d.where(F.col("lang").isin("de", "fr") & F.col("n_chars").between(500, 3000) & F.col("source").startswith("src1") & F.col("source").isNotNull()).select("doc_id", "lang", "n_chars")


@query("op_json_props_events", "SELECT event_type, sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS total, count(*) AS events FROM events GROUP BY event_type")
def _(spark, sf):
    e = t(spark, sf, "events").select("event_type", F.from_json("props", "k bigint").alias("p"))
    return e.groupBy("event_type").agg(F.sum("p.k").alias("total"), F.count(F.lit(1)).alias("events"))


@query("op_format_roundtrip", "SELECT format, n AS rows, keys FROM (SELECT unnest(['csv', 'json', 'orc']) AS format), (SELECT count(*) AS n, CAST(sum(n_nationkey) AS BIGINT) AS keys FROM nation)")
def _(spark, sf):
    n, out = t(spark, sf, "nation").select("n_nationkey", "n_name"), None
    for kind in ("csv", "json", "orc"):
        path = scratch(spark, kind)
        n.write.format(kind).save(path)
        row = spark.read.schema(n.schema).format(kind).load(path).agg(F.lit(kind).alias("format"), F.count(F.lit(1)).alias("rows"), F.sum("n_nationkey").cast("bigint").alias("keys"))
        out = row if out is None else out.union(row)
    return out


@query("op_bucketed_join", "SELECT o_orderstatus, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus")
def _(spark, sf):
    """Both sides are written as tables bucketed by the key, so the join that follows, and any later one, does not shuffle them."""
    sides = []
    for name, key, columns in (("orders", "o_orderkey", ["o_orderkey", "o_orderstatus"]), ("lineitem", "l_orderkey", ["l_orderkey"])):
        path = scratch(spark, f"bucketed-{name}")
        made = "tauprobe_" + path.rsplit("-", 1)[-1]
        t(spark, sf, name).select(*columns).write.bucketBy(BUCKETS, key).sortBy(key).option("path", path).saveAsTable(made)
        sides.append(spark.table(made))
    o, li = sides
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("lines"))


# ---- joins

_DUP = "WITH dup AS (SELECT md5(text) AS h FROM documents GROUP BY 1 HAVING count(*) > 1)"


def _copies(d: DataFrame) -> DataFrame:
    return d.groupBy(F.md5("text").alias("h")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h")


@query("op_join_semi_dup_docs", f"{_DUP} SELECT doc_id FROM documents WHERE md5(text) IN (SELECT h FROM dup)")
def _(spark, sf):
    d = t(spark, sf, "documents")
    return d.select("doc_id", F.md5("text").alias("h")).join(_copies(d), "h", "left_semi").select("doc_id")


@query("op_join_anti_unique_docs", f"{_DUP} SELECT doc_id FROM documents WHERE md5(text) NOT IN (SELECT h FROM dup)")
def _(spark, sf):
    d = t(spark, sf, "documents")
    return d.select("doc_id", F.md5("text").alias("h")).join(_copies(d), "h", "left_anti").select("doc_id")


@query("op_join_left_labels", "SELECT d.doc_id, quality, toxic FROM documents d LEFT JOIN labels l USING (doc_id)")
def _(spark, sf):
    return t(spark, sf, "documents").select("doc_id").join(t(spark, sf, "labels"), "doc_id", "left").select("doc_id", "quality", "toxic")


@query("op_join_broadcast_nation", "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark, sf):
    n = t(spark, sf, "nation").select("n_nationkey", "n_name")  # 25 nations, whatever the scale
    c = t(spark, sf, "customer").select("c_nationkey")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


@query("op_join_merge_orders_lineitem", "SELECT o_orderpriority, count(*) AS lines, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def _(spark, sf):
    o = t(spark, sf, "orders").select("o_orderkey", "o_orderpriority").hint("merge")
    li = t(spark, sf, "lineitem").select("l_orderkey", "l_quantity")
    return o.join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("lines"), F.sum("l_quantity").cast("bigint").alias("quantity"))


@query("op_join_range_nchars", "SELECT a.doc_id AS short_id, count(*) AS longer FROM documents a JOIN documents b ON a.lang = b.lang AND b.n_chars BETWEEN a.n_chars + 1 AND a.n_chars + 100 GROUP BY a.doc_id")
def _(spark, sf):
    """A range join over distinct lengths, not over rows: lengths fall into cells as wide as the range, and each looks into two of them."""
    d = t(spark, sf, "documents").select("doc_id", "lang", "n_chars").where("lang is not null and n_chars is not null")
    sizes = d.groupBy("lang", "n_chars").agg(F.count(F.lit(1)).alias("n"))
    cell = F.floor(F.col("n_chars") / 100)
    a = sizes.select("lang", F.col("n_chars").alias("lo"), F.explode(F.array(cell, cell + 1)).alias("cell"))
    b = sizes.select("lang", "n_chars", "n", cell.alias("cell"))
    longer = a.join(b, ["lang", "cell"]).where("n_chars between lo + 1 and lo + 100").groupBy("lang", F.col("lo").alias("n_chars")).agg(F.sum("n").alias("longer"))
    return d.join(longer, ["lang", "n_chars"]).groupBy(F.col("doc_id").alias("short_id")).agg(F.sum("longer").alias("longer"))


@query("op_join_interval_events", "SELECT a.event_id, count(*) AS followers FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def _(spark, sf):
    """Counts an interval join without its pairs: a user's hour and the one after it lie in one window, so a busy user is many tasks."""
    e = t(spark, sf, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us")).where("user_id is not null and us is not null")
    hour = F.floor(F.col("us") / 3_600_000_000)
    dealt = e.select("*", F.explode(F.array(hour, hour - 1)).alias("cell"), hour.alias("hour"))
    ahead = W.partitionBy("user_id", "cell").orderBy("us").rangeBetween(1, 3_600_000_000)
    counted = dealt.select("event_id", "cell", "hour", F.count(F.lit(1)).over(ahead).alias("n")).where("cell = hour and n > 0")
    return counted.groupBy("event_id").agg(F.sum("n").alias("followers"))


@query("op_join_asof_events", "SELECT p.event_id, max(v.event_id) AS last_view FROM events p JOIN events v ON v.user_id = p.user_id AND v.event_type = 'click' AND v.event_id < p.event_id WHERE p.event_type = 'purchase' GROUP BY p.event_id")
def _(spark, sf):
    """The last click of the same user before each purchase: one sort, no join."""
    e = t(spark, sf, "events").select("event_id", "user_id", "event_type")
    before = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(before)
    return e.select("event_id", "event_type", seen.alias("last_view")).where("event_type = 'purchase' and last_view is not null").select("event_id", "last_view")


@query("op_join_theta_emb", "SELECT a.vec_id AS id_a, b.vec_id AS id_b FROM embeddings a JOIN embeddings b ON a.label < b.label AND a.vec_id = b.vec_id - 1")
def _(spark, sf):
    e = t(spark, sf, "embeddings").select("vec_id", "label")
    a, b = e.select(F.col("vec_id").alias("id_a"), F.col("label").alias("la")), e.select(F.col("vec_id").alias("id_b"), F.col("label").alias("lb"))
    return a.join(b, (F.col("id_a") + 1 == F.col("id_b")) & (F.col("la") < F.col("lb"))).select("id_a", "id_b")


@query("op_lateral_topk", "SELECT c_custkey, o_orderkey, pos FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS pos FROM orders) WHERE pos <= 2")
def _(spark, sf):
    o = t(spark, sf, "orders")
    pos = F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return o.select(F.col("o_custkey").alias("c_custkey"), "o_orderkey", pos.cast("bigint").alias("pos")).where("pos <= 2")


# ---- aggregations

_RATES = "WITH m AS (SELECT doc_id, lang, source, count(*) OVER (PARTITION BY md5(text)) > 1 AS dup FROM documents)"


def _marked(spark, sf):
    d = t(spark, sf, "documents").select("doc_id", "lang", "source", F.md5("text").alias("h"))
    return d.join(_copies(t(spark, sf, "documents")).withColumn("dup", F.lit(1)), "h", "left").select("doc_id", "lang", "source", F.coalesce("dup", F.lit(0)).alias("dup"))


for _n, _how in (("op_agg_cube_dup_rate", "CUBE"), ("op_agg_rollup_lang_source", "ROLLUP")):

    @query(_n, f"{_RATES} SELECT lang, source, count(*) AS docs, round(avg(CASE WHEN dup THEN 1 ELSE 0 END), 6) AS dup_rate FROM m GROUP BY {_how} (lang, source)")
    def _(spark, sf, how=_how.lower()):
        return getattr(_marked(spark, sf), how)("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg("dup"), 6).alias("dup_rate"))


@query("op_agg_grouping_sets", f"{_RATES} SELECT lang, source, count(*) AS docs FROM m GROUP BY GROUPING SETS ((lang), (source), ())")
def _(spark, sf):
    return _marked(spark, sf).groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("docs"))


@query("op_agg_distinct", "SELECT lang, count(DISTINCT text) AS texts, count(DISTINCT source) AS sources FROM documents GROUP BY lang")
def _(spark, sf):
    return t(spark, sf, "documents").groupBy("lang").agg(F.count_distinct("text").alias("texts"), F.count_distinct("source").alias("sources"))


@query("op_agg_approx_distinct")
def _(spark, sf):
    return t(spark, sf, "documents").groupBy("lang").agg(F.approx_count_distinct("text", 0.02).alias("texts"))


@query("op_agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.5) AS p50, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")
def _(spark, sf):
    return t(spark, sf, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("p50"), F.percentile("n_chars", 0.9).alias("p90"))


@query("op_agg_max_by", "SELECT source, arg_max(doc_id, n_chars * 1000000 + doc_id) AS longest FROM documents GROUP BY source")
def _(spark, sf):
    return t(spark, sf, "documents").groupBy("source").agg(F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"))


@query("op_agg_histogram_map", "SELECT lang, to_json(map_from_entries(list((k, n) ORDER BY k))) AS histogram FROM (SELECT lang, CAST(n_chars // 5000 AS VARCHAR) AS k, count(*) AS n FROM documents GROUP BY ALL) GROUP BY lang")
def _(spark, sf):
    n = t(spark, sf, "documents").groupBy("lang", F.floor(F.col("n_chars") / 5000).cast("string").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy("lang").agg(F.to_json(F.map_from_entries(F.sort_array(F.collect_list(F.struct("k", "n"))))).alias("histogram"))


@query("op_agg_pivot_w", "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def _(spark, sf):
    return t(spark, sf, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count().na.fill(0)


@query("op_agg_vector_mean", "SELECT label, d, round(avg(x), 6) AS mean FROM (SELECT label, unnest(range(0, 64)) AS d, unnest(embedding) AS x FROM embeddings) GROUP BY label, d")
def _(spark, sf):
    return t(spark, sf, "embeddings").select("label", F.posexplode("embedding").alias("d", "x")).groupBy("label", F.col("d").cast("bigint").alias("d")).agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


# ---- windows

def _by_user():
    return W.partitionBy("user_id").orderBy("event_id")


@query("op_win_rank_family", "SELECT doc_id, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER x AS q, round(percent_rank() OVER w, 6) AS p FROM documents WINDOW w AS (PARTITION BY source ORDER BY lang), x AS (PARTITION BY source ORDER BY lang, doc_id)")
def _(spark, sf):
    w, x = W.partitionBy("source").orderBy("lang"), W.partitionBy("source").orderBy("lang", "doc_id")
    big = lambda c, n: c.cast("bigint").alias(n)
    return t(spark, sf, "documents").select("doc_id", big(F.rank().over(w), "r"), big(F.dense_rank().over(w), "d"), big(F.ntile(4).over(x), "q"), F.round(F.percent_rank().over(w), 6).alias("p"))


@query("op_win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def _(spark, sf):
    return t(spark, sf, "events").select("event_id", F.lag("event_type").over(_by_user()).alias("before"), F.lead("event_type").over(_by_user()).alias("after"))


@query("op_win_running_max", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY event_id) AS so_far FROM events")
def _(spark, sf):
    return t(spark, sf, "events").select("event_id", F.max("value").over(_by_user()).alias("so_far"))


@query("op_win_rows_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS n, min(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS least FROM events")
def _(spark, sf):
    w = _by_user().rowsBetween(-3, 0)
    return t(spark, sf, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"), F.min("value").over(w).alias("least"))


@query("op_win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(spark, sf):
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return t(spark, sf, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("op_win_islands_hits", "WITH m AS (SELECT user_id, event_type, event_id, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY event_id) AS g FROM events) SELECT user_id, event_type, min(event_id) AS first_id, count(*) AS length FROM m GROUP BY user_id, event_type, g HAVING count(*) >= 2")
def _(spark, sf):
    e = t(spark, sf, "events").select("user_id", "event_type", "event_id", (F.row_number().over(_by_user()) - F.row_number().over(W.partitionBy("user_id", "event_type").orderBy("event_id"))).alias("g"))
    return e.groupBy("user_id", "event_type", "g").agg(F.min("event_id").alias("first_id"), F.count(F.lit(1)).alias("length")).where("length >= 2").drop("g")


# ---- order and sets

@query("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("op_topk_per_query", "SELECT lang, doc_id, pos FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS pos FROM documents) WHERE pos <= 5")
def _(spark, sf):
    pos = F.row_number().over(W.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id"))
    return t(spark, sf, "documents").select("lang", "doc_id", pos.cast("bigint").alias("pos")).where("pos <= 5")


@query("op_sort_ties", "SELECT label, vec_id FROM embeddings ORDER BY label, vec_id DESC LIMIT 30")
def _(spark, sf):
    return t(spark, sf, "embeddings").select("label", "vec_id").orderBy("label", F.desc("vec_id")).limit(30)


def _two(spark, sf):
    d = t(spark, sf, "documents")
    return d.where("lang = 'en'").select("source"), d.where("n_chars > 8000").select("source")


for _n, _op, _f in (("union", "UNION", lambda a, b: a.union(b).distinct()), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):

    @query(f"op_set_{_n}", f"SELECT source FROM documents WHERE lang = 'en' {_op} SELECT source FROM documents WHERE n_chars > 8000")
    def _(spark, sf, f=_f):
        return f(*_two(spark, sf))


# ---- functions

@query("op_fn_string", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS plain_chars, lower(substr(url, 1, 12)) AS head, md5(url) AS m, sha256(url) AS s, levenshtein(substr(url, 1, 20), substr(url, 5, 20)) AS lev, len(regexp_extract_all(html, '<p>')) AS paragraphs FROM pages")
def _(spark, sf):
    big = lambda c: c.cast("bigint")
    return t(spark, sf, "pages").select(
        "page_id", big(F.length(F.regexp_replace("html", "<[^>]*>", ""))).alias("plain_chars"), F.lower(F.substring("url", 1, 12)).alias("head"), F.md5("url").alias("m"), F.sha2("url", 256).alias("s"),
        big(F.levenshtein(F.substring("url", 1, 20), F.substring("url", 5, 20))).alias("lev"), big(F.size(F.regexp_extract_all("html", F.lit("<p>"), 0))).alias("paragraphs"),
    )


@query("op_fn_math", "SELECT event_id, round(sqrt(abs(value)), 6) AS root, round(acos(least(1.0, abs(value) / 1000)), 6) AS angle, round(log2(abs(value) + 1), 6) AS lg, greatest(value, 10.0) AS g FROM events")
def _(spark, sf):
    v = F.abs("value")
    return t(spark, sf, "events").select("event_id", F.round(F.sqrt(v), 6).alias("root"), F.round(F.acos(F.least(F.lit(1.0), v / 1000)), 6).alias("angle"), F.round(F.log2(v + 1), 6).alias("lg"), F.greatest("value", F.lit(10.0)).alias("g"))


@query("op_fn_date", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS orders, max(date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE))) AS last_day FROM orders GROUP BY 1")
def _(spark, sf):
    o = t(spark, sf, "orders")
    return o.groupBy(F.substring(F.date_trunc("month", "o_orderdate").cast("string"), 1, 7).alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.max(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date"))).cast("bigint").alias("last_day"))


@query("op_fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding[1:8], lambda x: CAST(x AS DOUBLE) * x)), 6) AS part, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_max(list_transform(range(0, 5), lambda i: i * vec_id)) AS top FROM embeddings")
def _(spark, sf):
    e = t(spark, sf, "embeddings")
    square = lambda x: x.cast("double") * x.cast("double")
    return e.select(
        "vec_id", F.round(F.aggregate(F.transform(F.slice("embedding", 1, 8), square), F.lit(0.0), lambda a, x: a + x), 6).alias("part"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"),
        F.array_max(F.transform(F.sequence(F.lit(0), F.lit(4)), lambda i: i * F.col("vec_id"))).alias("top"),
    )


@query("op_fn_map", "SELECT source, count(*) FILTER (lang = 'en') AS english, count(DISTINCT lang) AS langs FROM documents GROUP BY source")
def _(spark, sf):
    m = t(spark, sf, "documents").groupBy("source", "lang").agg(F.count(F.lit(1)).alias("n")).groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return m.select("source", F.coalesce(F.try_element_at("m", F.lit("en")), F.lit(0)).alias("english"), F.size(F.map_filter("m", lambda k, v: v > 0)).cast("bigint").alias("langs"))


@query("op_fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(spark, sf):
    return t(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"))


@query("op_fn_bits", "SELECT doc_id, xor(h, h >> 7) AS mixed, bit_count(h) AS ones FROM (SELECT doc_id, ('0x' || substr(md5(text), 1, 8))::BIGINT AS h FROM documents)")
def _(spark, sf):
    d = t(spark, sf, "documents").select("doc_id", F.conv(F.substring(F.md5("text"), 1, 8), 16, 10).cast("bigint").alias("h"))
    return d.select("doc_id", F.col("h").bitwiseXOR(F.shiftright("h", 7)).alias("mixed"), F.bit_count("h").alias("ones"))


# ---- streams

@query("op_stream_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS events FROM events GROUP BY ALL")
def _(spark, sf):
    return ev.tumbling(spark, t(spark, sf, "events"))


@query("op_stream_sliding", "SELECT b + i * INTERVAL 30 MINUTE AS start, count(*) AS events FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS b FROM events), (SELECT unnest([-1, 0]) AS i) GROUP BY 1")
def _(spark, sf):
    return ev.sliding(spark, t(spark, sf, "events"))


@query("op_stream_session", "WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM m) SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, g")
def _(spark, sf):
    return ev.sessions(spark, t(spark, sf, "events"))


@query("op_stream_dedup", "SELECT count(DISTINCT (user_id, event_type)) AS kinds FROM events")
def _(spark, sf):
    return ev.dedup(spark, t(spark, sf, "events"))


@query("op_stream_stateful", "SELECT user_id, count(*) AS events FROM events GROUP BY user_id")
def _(spark, sf):
    return ev.stateful(spark, t(spark, sf, "events"))


@query("op_stream_late")
def _(spark, sf):
    return ev.late(spark, t(spark, sf, "events"))


@query("op_stream_static_join", "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark, sf):
    return ev.static_join(spark, t(spark, sf, "customer"), t(spark, sf, "nation"))


@query("op_stream_interval_join", "SELECT p.event_id AS purchase_id, c.event_id AS click_id FROM events p JOIN events c ON c.user_id = p.user_id AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR WHERE p.event_type = 'purchase' AND c.event_type = 'click'")
def _(spark, sf):
    return ev.interval_join(spark, t(spark, sf, "events"))


# ---- UDF surface

@query("op_udf_cosine", "SELECT a.vec_id, round(list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v) * list_dot_product(b.v, b.v)), 6) AS sim FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) a JOIN (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) b ON b.vec_id = a.vec_id + 1")
def _(spark, sf):
    registered.register(spark)
    e = t(spark, sf, "embeddings").select("vec_id", "embedding")
    e.createOrReplaceTempView("tauprobe_emb")
    return spark.sql("select a.vec_id, round(tau_cosine(a.embedding, b.embedding), 6) as sim from tauprobe_emb a join tauprobe_emb b on b.vec_id = a.vec_id + 1")


@query("op_pandas_udf_norm", "SELECT vec_id, round(sqrt(list_dot_product(v, v)), 6) AS norm FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)")
def _(spark, sf):
    registered.register(spark)
    return t(spark, sf, "embeddings").select("vec_id", F.round(F.call_function("tau_norm", "embedding"), 6).alias("norm"))


@query("op_udaf_mean", "SELECT label, round(avg(embedding[1]), 6) AS first_mean FROM embeddings GROUP BY label")
def _(spark, sf):
    """A Python aggregate sees its group whole, so groups are cut by id first and the parts' means are weighted."""
    e = t(spark, sf, "embeddings").where("embedding is not null")
    parts = e.groupBy("label", F.floor(F.col("vec_id") / 65_536).alias("part")).agg(registered.mean_first(F.col("embedding")).alias("mean"), registered.rows_of(F.col("embedding")).alias("n"))
    return parts.groupBy("label").agg(F.round(F.sum(F.col("mean") * F.col("n")) / F.sum("n"), 6).alias("first_mean"))


@query("op_udtf_probe_trace", "SELECT unnest([1, 2, 3, 4, 5, 6, 7, 8, 9, 10]) AS rank, unnest([1, 2, 0, 1, 2, 3, 4, 5, 6, 7]) AS stale, unnest([true, true, true, true, true, true, false, false, false, false]) AS visited")
def _(spark, sf):
    registered.register(spark)
    return spark.sql("select * from tau_probe_trace('0010000000', 3)")


@query("op_udtf_hashed_tokens", "SELECT doc_id, count(*) AS tokens FROM (SELECT doc_id, unnest(list_filter(regexp_split_to_array(text, '[ \\t\\r\\n]+'), lambda w: w <> '')) FROM documents) GROUP BY doc_id")
def _(spark, sf):
    registered.register(spark)
    t(spark, sf, "documents").select("doc_id", "text").createOrReplaceTempView("tauprobe_docs")
    return spark.sql("select doc_id, count(*) as tokens from tauprobe_docs, lateral tau_hashed_tokens(text) group by doc_id")


@query("op_map_in_arrow_search", "WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings), s AS (SELECT a.vec_id AS query_id, b.vec_id, list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v) * list_dot_product(b.v, b.v)) AS sim FROM v a, v b WHERE a.vec_id % 50 = 0 AND b.vec_id <> a.vec_id) SELECT query_id, vec_id FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, vec_id) = 1")
def _(spark, sf):
    from tauprobe.operators import search

    every, held = wl.split(wl.vectors_of(spark, sf, "emb"))
    return search.exact(every, held, -2.0, 1, drop_self=True).select("query_id", "vec_id")


# ---- star schema

@query("op_star_revenue_nation", "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark, sf):
    li = t(spark, sf, "lineitem").select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("r"))
    o, c = t(spark, sf, "orders").select("o_orderkey", "o_custkey"), t(spark, sf, "customer").select("c_custkey", "c_nationkey")
    n = F.broadcast(t(spark, sf, "nation").select("n_nationkey", "n_name"))  # 25 rows at any scale
    joined = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("n_name").agg(F.round(F.sum("r"), 2).alias("revenue"))


@query("op_pricing_summary", "SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS quantity, round(avg(l_discount), 4) AS discount, count(*) AS lines FROM lineitem GROUP BY ALL")
def _(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("bigint").alias("quantity"), F.round(F.avg("l_discount"), 4).alias("discount"), F.count(F.lit(1)).alias("lines"))
