"""The operators a user needs around the store, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trieaccess.sources import tables
from trieaccess.session import scratch_path
from trieaccess.sources.tables import load

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


@query("SELECT lang, count(*) AS n FROM documents WHERE n_chars BETWEEN 500 AND 5000 AND lang IN ('en', 'de') AND regexp_matches(source, '^src1') GROUP BY lang")
def filter_docs(spark, d):
    t = load(spark, d, "documents", "lang", "source", "n_chars")
    return t.where(F.col("n_chars").between(500, 5000) & F.col("lang").isin("en", "de") & F.col("source").rlike("^src1")).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, CASE WHEN n_chars < 1000 THEN 'short' WHEN n_chars < 10000 THEN 'mid' ELSE 'long' END AS size_class FROM documents")
def size_class(spark, d):
    return load(spark, d, "documents", "doc_id", "n_chars").select("doc_id", F.when(F.col("n_chars") < 1000, "short").when(F.col("n_chars") < 10000, "mid").otherwise("long").alias("size_class"))


@query("SELECT r_name, n_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def broadcast_join(spark, d):
    """Nations and regions are fixed lists."""
    return load(spark, d, "nation").join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("r_name", "n_name")


def _docs_labels(spark, d, hint):
    return load(spark, d, "documents", "doc_id", "lang").join(load(spark, d, "labels").hint(hint), "doc_id").groupBy("lang").agg(F.sum("toxic").alias("toxic"), F.count(F.lit(1)).alias("n"))


_JOIN = "SELECT lang, CAST(sum(toxic) AS BIGINT) AS toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY lang"


@query(_JOIN)
def merge_join(spark, d):
    return _docs_labels(spark, d, "merge")


@query(_JOIN)
def shuffle_hash_join(spark, d):
    return _docs_labels(spark, d, "shuffle_hash")


def _coverage(how, sql):
    def f(spark, d):
        a, b = load(spark, d, "documents", "doc_id", "lang"), load(spark, d, "labels").where("quality = 1")
        return a.where("lang <> 'es'").join(b, "doc_id", how).select("doc_id", "lang", "quality")

    f.__name__ = f"join_{how}"
    query(f"SELECT doc_id, lang, quality FROM (SELECT doc_id, lang FROM documents WHERE lang <> 'es') a {sql} JOIN (SELECT * FROM labels WHERE quality = 1) b USING (doc_id)")(f)


_coverage("left", "LEFT")
_coverage("right", "RIGHT")
_coverage("full", "FULL")


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, d):
    return load(spark, d, "documents", "doc_id").join(load(spark, d, "labels", "doc_id"), "doc_id", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, d):
    return load(spark, d, "documents", "doc_id").join(load(spark, d, "labels", "doc_id"), "doc_id", "left_anti")


@query("""SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE""")
def interval_join(spark, d):
    """Bucketed: an event meets only those of its own and the next time bucket of its user."""
    e = load(spark, d, "events", "event_id", "user_id", "ts").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    wide = 600 * 1_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("s").alias("sa"), F.explode(F.array(F.floor(F.col("s") / wide), F.floor(F.col("s") / wide) + 1)).alias("k"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("s").alias("sb"), F.floor(F.col("s") / wide).alias("k"))
    return a.join(b, ["user_id", "k"]).where((F.col("sb") > F.col("sa")) & (F.col("sb") <= F.col("sa") + wide)).select("a", "b")


@query("SELECT o.o_orderkey, (SELECT max(e.event_id) FROM events e WHERE e.user_id = o.o_custkey AND e.ts <= o.o_orderdate + INTERVAL 3650 DAY) AS last_event FROM orders o")
def asof_join(spark, d):
    """The last event of the customer up to ten years after the order: union and one sorted window."""
    o = load(spark, d, "orders", F.col("o_custkey").alias("k"), (F.col("o_orderdate") + F.expr("INTERVAL 3650 DAY")).alias("t"), "o_orderkey")
    e = load(spark, d, "events", F.col("user_id").alias("k"), F.col("ts").alias("t"), "event_id")
    both = o.select("k", "t", F.lit(1).alias("tag"), "o_orderkey", F.lit(None).cast("long").alias("event_id")).unionByName(e.select("k", "t", F.lit(0).alias("tag"), F.lit(None).cast("long").alias("o_orderkey"), "event_id"))
    w = Window.partitionBy("k").orderBy("t", "tag").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last_event", F.max("event_id").over(w)).where("tag = 1").select("o_orderkey", "last_event")


@query("SELECT d.doc_id, p.item_id FROM documents d JOIN benchmark p ON contains(d.text, p.text)")
def passages_in_docs(spark, d):
    """By the passages' first symbols, and an exact check."""
    from .passages import occurrences

    found = occurrences(load(spark, d, "documents", F.col("doc_id").alias("seq_id"), "text"), load(spark, d, "benchmark", "item_id", F.col("text").alias("passage")))
    return found.select(F.col("seq_id").alias("doc_id"), "item_id")


@query("SELECT a.doc_id, count(*) AS n FROM labels a JOIN labels b ON a.doc_id = b.doc_id GROUP BY a.doc_id")
def self_join(spark, d):
    t = load(spark, d, "labels", "doc_id")
    return t.alias("a").join(t.alias("b"), F.expr("a.doc_id = b.doc_id")).groupBy("a.doc_id").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS qty, count(*) AS n, min(l_shipdate) AS first_ship FROM lineitem GROUP BY l_returnflag, l_linestatus")
def hash_aggregate(spark, d):
    t = load(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_shipdate")
    return t.groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("long").alias("qty"), F.count(F.lit(1)).alias("n"), F.min("l_shipdate").alias("first_ship"))


@query("SELECT count(DISTINCT c) AS symbols FROM (SELECT unnest(regexp_extract_all(text, '(?s).')) AS c FROM documents)")
def symbol_cardinality(spark, d):
    return load(spark, d, "documents", "text").select(F.explode(F.split("text", "")).alias("c")).where("c <> ''").agg(F.count_distinct("c").alias("symbols"))


@query()
def approx_users(spark, d):
    return load(spark, d, "events", "user_id").agg(F.approx_count_distinct("user_id", 0.01).alias("about"), F.count_distinct("user_id").alias("exact"))


@query("SELECT lang, CAST(quantile_cont(n_chars, 0.5) AS DOUBLE) AS p50, CAST(quantile_cont(n_chars, 0.9) AS DOUBLE) AS p90 FROM documents GROUP BY lang")
def length_percentiles(spark, d):
    return load(spark, d, "documents", "lang", "n_chars").groupBy("lang").agg(F.median("n_chars").alias("p50"), F.percentile("n_chars", F.lit(0.9)).alias("p90"))


@query("SELECT lang, arg_max(doc_id, n_chars * 1000000 - doc_id) AS longest, count(*) FILTER (n_chars > 1000) AS over_1000 FROM documents GROUP BY lang")
def longest_per_lang(spark, d):
    t = load(spark, d, "documents", "lang", "doc_id", "n_chars")
    return t.groupBy("lang").agg(F.max_by("doc_id", F.col("n_chars") * 1000000 - F.col("doc_id")).alias("longest"), F.count_if(F.col("n_chars") > 1000).alias("over_1000"))


@query("SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def concat_turns(spark, d):
    load(spark, d, "conversations", "conv_id", "turn", "role").createOrReplaceTempView("_conv")
    return spark.sql("SELECT conv_id, listagg(role, '>') WITHIN GROUP (ORDER BY turn) AS roles FROM _conv GROUP BY conv_id")


@query("SELECT lang, source, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def sizes_rollup(spark, d):
    return load(spark, d, "documents", "lang", "source", "n_chars").rollup("lang", "source").agg(F.sum("n_chars").alias("chars"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def sizes_cube(spark, d):
    return load(spark, d, "documents", "lang", "source").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def sizes_grouping_sets(spark, d):
    load(spark, d, "documents", "lang", "source").createOrReplaceTempView("_docs")
    return spark.sql("SELECT lang, source, count(*) AS n FROM _docs GROUP BY GROUPING SETS ((lang), (source), ())")


@query("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'de') AS de FROM documents GROUP BY source")
def pivot_langs(spark, d):
    t = load(spark, d, "documents", "source", "lang").groupBy("source").pivot("lang", ["en", "de"]).agg(F.count(F.lit(1)))
    return t.select("source", F.coalesce("en", F.lit(0)).alias("en"), F.coalesce("de", F.lit(0)).alias("de"))


_RANK = "(PARTITION BY source ORDER BY n_chars DESC, doc_id)"


@query(f"SELECT doc_id, row_number() OVER {_RANK} AS rn, rank() OVER {_RANK} AS rk, dense_rank() OVER {_RANK} AS dr, ntile(4) OVER {_RANK} AS q, percent_rank() OVER {_RANK} AS pr, cume_dist() OVER {_RANK} AS cd FROM documents")
def windows_ranking(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return load(spark, d, "documents", "doc_id", "source", "n_chars").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("q"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


_EV = "(PARTITION BY user_id ORDER BY event_id"


@query(f"""SELECT event_id, lag(event_id) OVER {_EV}) AS prev, lead(event_id) OVER {_EV}) AS next, first_value(event_id) OVER {_EV}) AS first,
  last_value(event_id) OVER {_EV} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last, nth_value(event_id, 2) OVER {_EV} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events""")
def windows_analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "events", "event_id", "user_id").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id").over(w).alias("next"), F.first("event_id").over(w).alias("first"), F.last("event_id").over(full).alias("last"), F.nth_value("event_id", 2).over(full).alias("second"))


@query(f"SELECT event_id, count(*) OVER {_EV} ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS n4, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS near FROM events")
def windows_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return load(spark, d, "events", "event_id", "user_id").select("event_id", F.count(F.lit(1)).over(w.rowsBetween(-3, 0)).alias("n4"), F.count(F.lit(1)).over(w.rangeBetween(-1000, 0)).alias("near"))


@query("SELECT doc_id, CAST(sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT) AS off FROM documents")
def running_offsets(spark, d):
    """Where each document starts in its source's concatenation."""
    w = Window.partitionBy("source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)
    return load(spark, d, "documents", "doc_id", "source", "n_chars").select("doc_id", F.sum("n_chars").over(w).alias("off"))


@query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10")
def topk_docs(spark, d):
    return load(spark, d, "documents", "doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(10)


@query("SELECT source, doc_id FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS k FROM documents) WHERE k <= 3")
def topk_per_source(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return load(spark, d, "documents", "doc_id", "source", "n_chars").withColumn("k", F.row_number().over(w)).where("k <= 3").select("source", "doc_id")


def _words(spark, d, lang):
    t = load(spark, d, "documents", "text", "lang").where(F.col("lang") == lang)
    return t.select(F.explode(F.split(F.lower("text"), r"[\x20\x09-\x0D]+")).alias("w")).where("w <> ''")


def _words_sql(lang):
    return rf"SELECT unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS w FROM documents WHERE lang = '{lang}'"


def _setop(name, op, sql):
    def f(spark, d):
        return op(_words(spark, d, "en"), _words(spark, d, "de")).groupBy("w").agg(F.count(F.lit(1)).alias("n"))

    f.__name__ = name
    query(f"SELECT w, count(*) AS n FROM ({_words_sql('en')} {sql} {_words_sql('de')}) GROUP BY w")(f)


_setop("set_intersect", lambda a, b: a.intersect(b), "INTERSECT")
_setop("set_except", lambda a, b: a.subtract(b), "EXCEPT")
_setop("set_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL")
_setop("set_except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL")
_setop("set_union_all", lambda a, b: a.unionByName(b), "UNION ALL")


@query("SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8) AS BIGINT) % 10 = 0")
def sample_requests(spark, d):
    """A reproducible tenth: sampling by a hash of the id."""
    return load(spark, d, "documents", "doc_id").where(F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % 10 == 0)


@query("""SELECT doc_id, CAST(length(text) AS INTEGER) AS chars, CAST(octet_length(encode(text)) AS INTEGER) AS bytes, substr(text, 3, 5) AS mid, CAST(instr(text, 'the') AS INTEGER) AS at, reverse(left(text, 10)) AS back,
  translate(left(text, 20), 'aeiou', 'AEIOU') AS vowels, md5(text) AS digest, lpad(CAST(doc_id AS VARCHAR), 8, '0') AS padded, regexp_replace(left(text, 30), '[^A-Za-z]', '', 'g') AS letters FROM documents""")
def text_features(spark, d):
    t = load(spark, d, "documents", "doc_id", "text")
    return t.select("doc_id", F.length("text").alias("chars"), F.octet_length("text").alias("bytes"), F.substring("text", 3, 5).alias("mid"), F.instr("text", "the").alias("at"), F.reverse(F.expr("left(text, 10)")).alias("back"),
                    F.translate(F.expr("left(text, 20)"), "aeiou", "AEIOU").alias("vowels"), F.md5(F.col("text").cast("binary")).alias("digest"), F.lpad(F.col("doc_id").cast("string"), 8, "0").alias("padded"),
                    F.regexp_replace(F.expr("left(text, 30)"), "[^A-Za-z]", "").alias("letters"))


@query("SELECT p_partkey, CAST(bit_count(p_partkey) AS INTEGER) AS ones, p_partkey % 7 AS m, p_partkey << 3 AS eight, bin(p_partkey) AS bits, CAST(ceil(log2(p_partkey + 1)) AS BIGINT) AS width FROM part")
def bit_functions(spark, d):
    k = F.col("p_partkey")
    return load(spark, d, "part", "p_partkey").select(k, F.bit_count(k).cast("int").alias("ones"), F.pmod(k, F.lit(7)).alias("m"), F.shiftleft(k, 3).alias("eight"), F.bin(k).alias("bits"), F.ceil(F.log2(k + 1)).alias("width"))


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n, CAST(max(epoch_us(ts)) AS BIGINT) AS last_us FROM events GROUP BY 1")
def events_by_day(spark, d):
    t = load(spark, d, "events", "ts")
    return t.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count(F.lit(1)).alias("n"), F.max(F.unix_micros(F.col("ts").cast("timestamp"))).alias("last_us"))


@query("SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, CAST(max(date_diff('day', TIMESTAMP '1990-01-01', o_orderdate)) AS BIGINT) AS days FROM orders GROUP BY 1".replace("SELECT date_trunc('month', o_orderdate)", "SELECT CAST(date_trunc('month', o_orderdate) AS TIMESTAMP)"))
def orders_by_month(spark, d):
    load(spark, d, "orders", "o_orderdate").createOrReplaceTempView("_orders")
    return spark.sql("SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, max(CAST(datediff(o_orderdate, DATE '1990-01-01') AS BIGINT)) AS days FROM _orders GROUP BY 1")


@query("SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, list_transform(embedding[1:4], lambda x: CAST(floor(x * 16) AS BIGINT)) AS bins FROM embeddings")
def array_functions(spark, d):
    t = load(spark, d, "embeddings", "vec_id", "embedding")
    return t.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.transform(F.slice("embedding", 1, 4), lambda x: F.floor(x.cast("double") * 16)).alias("bins"))


@query("SELECT role, lang_len, n FROM (SELECT role, length(role) AS lang_len, count(*) AS n FROM conversations GROUP BY 1, 2)".replace("length(role)", "CAST(length(role) AS INTEGER)"))
def map_functions(spark, d):
    """A map of counts a role, flattened again."""
    t = load(spark, d, "conversations", "role").groupBy("role").agg(F.count(F.lit(1)).alias("n"))
    m = t.agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("m"))  # one entry a role
    return m.select(F.explode(F.map_filter(F.transform_values("m", lambda k, v: v), lambda k, v: v > 0)).alias("role", "n")).select("role", F.length("role").alias("lang_len"), "n")


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def events_props_json(spark, d):
    return load(spark, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT l_orderkey, sum(CAST(l_extendedprice AS DECIMAL(18,4)) * (1 - CAST(l_discount AS DECIMAL(6,4)))) AS revenue FROM lineitem GROUP BY l_orderkey".replace("sum(", "CAST(sum(").replace(") AS revenue", ") AS DECIMAL(38,8)) AS revenue"))
def revenue_decimal(spark, d):
    t = load(spark, d, "lineitem", "l_orderkey", "l_extendedprice", "l_discount")
    price = F.col("l_extendedprice").cast("decimal(18,4)") * (F.lit(1).cast("decimal(6,4)") - F.col("l_discount").cast("decimal(6,4)"))
    return t.groupBy("l_orderkey").agg(F.sum(price).cast("decimal(38,8)").alias("revenue"))


@query("WITH RECURSIVE r(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 15) SELECT n, f FROM r")
def recursive_query(spark, d):
    return spark.sql("WITH RECURSIVE r(n, f) AS (SELECT 1, 1L UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 15) SELECT n, f FROM r")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS hour, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def events_tumbling(spark, d):
    t = load(spark, d, "events", "ts", "event_type")
    return t.groupBy(F.window("ts", "1 hour")["start"].alias("hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT h - k * INTERVAL 30 MINUTE AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS h FROM events), range(2) r(k) GROUP BY 1")
def events_sliding(spark, d):
    return load(spark, d, "events", "ts").groupBy(F.window("ts", "1 hour", "30 minutes")["start"].alias("start")).agg(F.count(F.lit(1)).alias("n"))


@query("""SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
  (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def events_session(spark, d):
    t = load(spark, d, "events", "user_id", "ts")
    return t.groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


@query("SELECT l_orderkey // 1024 AS seq_id, length(t) AS n, md5(t) AS text_md5 FROM (SELECT l_orderkey // 1024 AS l_orderkey, string_agg(l_returnflag || l_linestatus, '' ORDER BY l_orderkey, l_linenumber, l_returnflag || l_linestatus) AS t FROM lineitem GROUP BY 1)".replace("(SELECT l_orderkey // 1024 AS l_orderkey,", "(SELECT min(l_orderkey) AS l_orderkey,").replace("GROUP BY 1)", "GROUP BY l_orderkey // 1024)"))
def columns_as_text(spark, d):
    """Two columns of a table as strings of its rows' order, a string for each 1,024 orders, compressed and read back."""
    from trieaccess.operators import codec

    t = load(spark, d, "lineitem", "l_orderkey", "l_linenumber", F.concat("l_returnflag", "l_linestatus").alias("flags"))
    parts = F.transform(F.array_sort(F.collect_list(F.struct("l_orderkey", "l_linenumber", "flags"))), lambda x: x["flags"])  # the lines of 1,024 orders
    seqs = t.groupBy(F.floor(F.col("l_orderkey") / 1024).alias("seq_id")).agg(F.array_join(parts, "").alias("text"))
    back = codec.expand(codec.compress(codec.cut(seqs), "dense"))
    return back.select("seq_id", F.length("text").cast("long").alias("n"), F.md5(F.col("text").cast("binary")).alias("text_md5"))


@query("SELECT n_name FROM nation")
def roundtrip_text(spark, d):
    out = f"{scratch_path(spark, "q")}/text"
    tables.write_any(load(spark, d, "nation", F.col("n_name").alias("value")), "text", out)
    return tables.read_any(spark, "text", out, "value string").select(F.col("value").alias("n_name"))


def _format(fmt):
    def f(spark, d):
        out = f"{scratch_path(spark, "q")}/{fmt}"
        t = load(spark, d, "nation", "n_nationkey", "n_name", "n_regionkey")
        tables.write_any(t, fmt, out)
        return tables.read_any(spark, fmt, out, "n_nationkey int, n_name string, n_regionkey int")

    f.__name__ = f"roundtrip_{fmt}"
    query("SELECT n_nationkey, n_name, n_regionkey FROM nation")(f)


for _fmt in ("csv", "json", "orc", "parquet"):
    _format(_fmt)


@query("SELECT doc_id AS seq_id, substr(text, 510, 7) AS piece FROM documents WHERE length(text) >= 510")
def store_source(spark, d):
    """A store written as files; the same range of every sequence read from the segments that hold it, with a capacity that cuts ranges."""
    from trieaccess.operators import codec
    from trieaccess.sources import store

    docs = codec.sequences(load(spark, d, "documents", "doc_id", "text"), "doc_id")
    path = f"{scratch_path(spark, "q")}/store"
    store.write(codec.compress(codec.cut(docs, 512), "dense", capacity=512), path)
    return store.read_ranges(spark, path, 510, 7, 512)


# streams: each replays a table and must equal the batch result
def _stream(df, build, files=3):
    from trieaccess.streaming import replay

    return replay(df.sparkSession, df, build, scratch_path(df.sparkSession, "stream"), files)


@query("SELECT event_id, event_type FROM events WHERE event_type = 'click'")
def stream_filter(spark, d):
    return _stream(load(spark, d, "events", "event_id", "event_type"), lambda s: s.where("event_type = 'click'"))


@query("SELECT DISTINCT event_id FROM events")
def stream_dedup(spark, d):
    t = load(spark, d, "events", "event_id", F.col("ts").cast("timestamp").alias("ts"))
    return _stream(t.unionByName(t), lambda s: s.withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@query("SELECT count(*) AS kept FROM (SELECT event_id, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR AS closed FROM events) WHERE event_id % 2 = 1 OR NOT closed")
def stream_events_late(spark, d):
    """Odd events come first; even ones whose hour is behind the watermark are late and are not counted any more."""
    from trieaccess.streaming import replay

    t = load(spark, d, "events", "event_id", F.col("ts").cast("timestamp").alias("ts"))
    last = t.agg(F.max("ts").alias("ts"))
    marks = [last.select(F.lit(None).cast("long").alias("event_id"), (F.col("ts") + F.expr(f"INTERVAL {days} DAY")).alias("ts"), F.lit(no).alias("no")) for days, no in ((0, 0), (0, 1), (2, 3))]  # a row each moves the watermark on, which drops late rows one batch later
    rows = t.withColumn("no", 2 - 2 * (F.col("event_id") % 2).cast("int")).unionByName(marks[0]).unionByName(marks[1]).unionByName(marks[2])

    def build(s):
        hours = s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w"))
        return hours.agg(F.count("event_id").alias("n")).select(F.col("w.start").alias("hour"), "n")

    return replay(spark, rows, build, scratch_path(spark, "late"), 4, "no").agg(F.sum("n").alias("kept"))


@query("SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, d):
    c = load(spark, d, "customer", "c_custkey", "c_name")
    return _stream(load(spark, d, "events", "event_id", "user_id"), lambda s: s.join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"))


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_stream_join(spark, d):
    from trieaccess.streaming import replay

    t = load(spark, d, "events", "event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")

    def build(s):
        a = s.where("event_type = 'click'").withWatermark("ts", "365 days").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
        b = s.where("event_type = 'purchase'").withWatermark("ts", "365 days").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
        return a.join(b, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 1 HOUR")).select("a", "b")

    return replay(spark, t, build, scratch_path(spark, "q"), 3)
