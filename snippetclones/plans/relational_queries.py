"""Registered queries of the operators around the methods: scans, sinks, joins, aggregates, windows, sets, functions, SQL."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import Window as Wd
from pyspark.sql import functions as F

from ..functions import normalize as N
from ..operators import cmw
from ..session import shared_dir
from ..sources import notebooks as nb, segment as seg
from .registry import query
from .sqltext import BLOCK_CELLS, with_ as W


def T(s, d, name):
    return seg.table(s, d, name)


def lines(s, d):
    return cmw.non_empty(seg.doc_lines(s, d))


def folder(s, stem):
    return f"{shared_dir(s).rstrip('/')}/{stem}_{uuid.uuid4().hex}"


# --- sources and sinks -----------------------------------------------------
@query("n:l lo:l hi:l", "SELECT count(*) AS n, min(doc_id) AS lo, max(doc_id) AS hi FROM documents")
def scan_parquet(s, d):
    return T(s, d, "documents").agg(F.count("*").alias("n"), F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"))


@query("nb_id:l readable:b cells:l", "SELECT doc_id AS nb_id, doc_id % 71 <> 0 AS readable, CASE WHEN doc_id % 71 <> 0 THEN len(string_split(text, chr(10))) END AS cells FROM documents")
def scan_json(s, d):
    """All bodies are written and read; the parser says which are damaged (the builder cuts every 71st short)."""
    p = folder(s, "json")
    nb.raw_notebooks(s, d).select("nb_id", "body").write.json(p)
    return nb.parse(s.read.schema("nb_id BIGINT, body STRING").json(p)).select("nb_id", "readable", F.when(F.col("readable"), F.size("n.cells")).alias("cells"))


@query("a:l b:l", "SELECT doc_id AS a, doc_id + 1 AS b FROM documents")
def scan_text(s, d):
    p = folder(s, "text")
    T(s, d, "documents").select(F.concat_ws(",", "doc_id", F.col("doc_id") + 1).alias("value")).write.text(p)
    v = F.split("value", ",")
    return nb.read_pair_lines(s, p).select(v[0].cast("long").alias("a"), v[1].cast("long").alias("b"))


@query("n_nationkey:l n_name:s r_name:s", "SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def scan_csv(s, d):
    p = folder(s, "csv")
    T(s, d, "nation").write.csv(p, header=True)
    n = s.read.schema("n_nationkey INT, n_name STRING, n_regionkey INT").csv(p, header=True)
    r = T(s, d, "region")
    return n.join(r, n["n_regionkey"] == r["r_regionkey"]).select("n_nationkey", "n_name", "r_name")


@query("files:l sized:b")
def scan_binaryfile(s, d):
    p = folder(s, "bin")
    T(s, d, "documents").select("text").write.text(p)
    f = s.read.format("binaryFile").option("pathGlobFilter", "*.txt").load(p)
    return f.agg(F.count("*").alias("files"), F.bool_and(F.col("length") == F.length("content")).alias("sized"))


@query("nb_id:l pos:l", W("SELECT nb_id, pos FROM cells WHERE lang = 'fr'", "cells"))
def sink_partitioned(s, d):
    p = folder(s, "parts")
    nb.sink_partitioned(seg.doc_lines(s, d), p)
    return s.read.parquet(p).where("lang = 'fr'").select("nb_id", "pos")


@query("h:s size:l", W("SELECT h, count(*) AS size FROM ne GROUP BY h", "ne"))
def sink_bucketed(s, d):
    name = f"cells_{uuid.uuid4().hex}"
    nb.sink_bucketed(lines(s, d).select("nb_id", "h"), name)
    return s.table(name).groupBy("h").agg(F.count("*").alias("size"))


# --- filters and joins -----------------------------------------------------
@query("doc_id:l ratio:d", "SELECT doc_id, n_chars / 1000.0 AS ratio FROM documents WHERE lang = 'en' AND n_chars BETWEEN 100 AND 5000")
def project_filter(s, d):
    return T(s, d, "documents").where("lang = 'en' AND n_chars BETWEEN 100 AND 5000").select("doc_id", (F.col("n_chars") / 1000.0).alias("ratio"))


@query("event_id:l", "SELECT event_id FROM events WHERE (event_type LIKE 'c%' OR props IS NULL OR user_id IN (1, 2, 3)) AND value IS NOT DISTINCT FROM value")
def filter_null_in_like(s, d):
    return T(s, d, "events").where("(event_type LIKE 'c%' OR props IS NULL OR user_id IN (1, 2, 3)) AND value <=> value")


@query("nb_id:l pos:l size:l", W("SELECT nb_id, pos, size FROM flags", "flags"))
def join_inner_hash(s, d):
    c = lines(s, d)
    return c.join(c.groupBy("h").agg(F.count("*").alias("size")).hint("shuffle_hash"), "h")


@query("o_orderkey:l lines:l", "SELECT o_orderkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_sortmerge(s, d):
    o, l = T(s, d, "orders"), T(s, d, "lineitem").hint("merge")
    return o.join(l, o["o_orderkey"] == l["l_orderkey"]).groupBy("o_orderkey").agg(F.count("*").alias("lines"))


@query("r_name:s customers:l", "SELECT r_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def join_broadcast(s, d):
    c, n, r = T(s, d, "customer"), T(s, d, "nation"), T(s, d, "region")
    dim = F.broadcast(n.join(r, n["n_regionkey"] == r["r_regionkey"]).select("n_nationkey", "r_name"))  # 25 rows at any scale
    return c.join(dim, c["c_nationkey"] == dim["n_nationkey"]).groupBy("r_name").agg(F.count("*").alias("customers"))


@query("o_orderkey:l lines:l", "SELECT o_orderkey, count(l_orderkey) AS lines FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_left(s, d):
    l = T(s, d, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.count("*").alias("lines"))
    return T(s, d, "orders").select("o_orderkey").join(l, "o_orderkey", "left").na.fill(0)


@query("doc_id:l in_docs:b in_labels:b", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NOT NULL AS in_docs, l.doc_id IS NOT NULL AS in_labels FROM documents d FULL JOIN (SELECT DISTINCT doc_id FROM labels) l ON d.doc_id = l.doc_id")
def join_full(s, d):
    a = T(s, d, "documents").select("doc_id", F.lit(True).alias("in_docs"))
    return a.join(T(s, d, "labels").select("doc_id", F.lit(True).alias("in_labels")).distinct(), "doc_id", "full_outer").na.fill(False)


@query("doc_id:l", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(s, d):
    return T(s, d, "documents").join(T(s, d, "labels"), "doc_id", "left_semi")


@query("doc_id:l", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(s, d):
    return T(s, d, "documents").join(T(s, d, "labels"), "doc_id", "left_anti")


@query("a:l b:l", "SELECT x.doc_id AS a, y.doc_id AS b FROM documents x JOIN documents y ON x.lang = y.lang AND x.doc_id < y.doc_id AND x.source = y.source AND 10 * least(x.n_chars, y.n_chars) >= 8 * greatest(x.n_chars, y.n_chars)")
def join_theta_range(s, d):
    """Size-band join: logarithmic length buckets make the range an equi-join on neighbouring buckets."""
    b = F.floor(F.log(F.greatest(F.col("n_chars"), F.lit(1))) / F.log(F.lit(1.25))).cast("int")
    x = T(s, d, "documents").select("lang", "source", F.col("doc_id").alias("a"), F.col("n_chars").alias("na"), b.alias("k"))
    y = T(s, d, "documents").select("lang", "source", F.col("doc_id").alias("b"), F.col("n_chars").alias("nb"), F.explode(F.sequence(b - 1, b + 1)).alias("k"))
    return x.join(y, ["lang", "source", "k"]).where("a < b AND 10 * least(na, nb) >= 8 * greatest(na, nb)")


@query("r_name:s theta:l", "SELECT r_name, theta FROM region JOIN (SELECT unnest([7, 8, 9]) AS theta) ON r_regionkey < theta - 6")
def join_nested_loop(s, d):
    return T(s, d, "region").join(F.broadcast(s.range(7, 10).toDF("theta")), F.col("r_regionkey") < F.col("theta") - 6)  # three rows


@query("g1:s g2:s", "SELECT a.lang AS g1, b.lang AS g2 FROM (SELECT DISTINCT lang FROM documents) a, (SELECT DISTINCT lang FROM documents) b")
def join_cross(s, d):
    """The skeleton of a group-by-group matrix: a handful of languages on either side."""
    g = T(s, d, "documents").select("lang").distinct()
    return g.toDF("g1").crossJoin(g.toDF("g2"))


@query("event_id:l earlier:l", "SELECT event_id, coalesce(lag(event_id) OVER (PARTITION BY user_id, event_type, props ORDER BY ts, event_id), -1) AS earlier FROM events")
def join_asof(s, d):
    w = Wd.partitionBy("user_id", "event_type", "props").orderBy("ts", "event_id")
    return T(s, d, "events").withColumn("earlier", F.coalesce(F.last("event_id", True).over(w.rowsBetween(Wd.unboundedPreceding, -1)), F.lit(-1)))


@query("a:l b:l", "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.event_type = y.event_type AND x.props IS NOT DISTINCT FROM y.props AND x.user_id <> y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE")
def join_interval(s, d):
    """Equal snippets of two users within ten minutes: the time bucket joins the key, so a hot key is cut by time."""
    e = T(s, d, "events").select("event_id", "user_id", F.concat_ws("#", "event_type", "props").alias("k"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = 600_000_000
    x = e.select("k", F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("t").alias("ta"), F.explode(F.array(F.floor(F.col("t") / w), F.floor(F.col("t") / w) + 1)).alias("slot"))
    y = e.select("k", F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("t").alias("tb"), F.floor(F.col("t") / w).alias("slot"))
    return x.join(y, ["k", "slot"]).where(f"ua <> ub AND tb > ta AND tb <= ta + {w}")


# --- aggregates ------------------------------------------------------------
@query("lang:s source:s n:l total:l mean:d lo:l hi:l sd:d", "SELECT lang, source, count(*) AS n, sum(n_chars) AS total, avg(n_chars) AS mean, min(n_chars) AS lo, max(n_chars) AS hi, stddev_samp(n_chars) AS sd FROM documents GROUP BY 1, 2")
def agg_partial_final(s, d):
    c = F.col("n_chars")
    return T(s, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"), F.sum(c).alias("total"), F.avg(c).alias("mean"), F.min(c).alias("lo"), F.max(c).alias("hi"), F.stddev_samp(c).alias("sd"))


@query("nb_id:l hs:s", W("SELECT nb_id, string_agg(h, ',' ORDER BY pos) AS hs FROM ne GROUP BY nb_id", "ne"))
def agg_sort_based(s, d):
    return lines(s, d).groupBy("nb_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "h"))), lambda x: x["h"]), ",").alias("hs"))


@query("h:s nbs:l repos:l langs:l", W("SELECT h, count(DISTINCT nb_id) AS nbs, count(DISTINCT repo) AS repos, count(DISTINCT lang) AS langs FROM ne GROUP BY h", "ne"))
def agg_distinct(s, d):
    return lines(s, d).groupBy("h").agg(F.count_distinct("nb_id").alias("nbs"), F.count_distinct("repo").alias("repos"), F.count_distinct("lang").alias("langs"))


@query("source:s small:l large:l", "SELECT source, count_if(n_chars < 1000) AS small, count(*) FILTER (WHERE n_chars >= 1000) AS large FROM documents GROUP BY 1")
def agg_filter(s, d):
    return T(s, d, "documents").groupBy("source").agg(F.count_if(F.col("n_chars") < 1000).alias("small"), F.expr("count(*) FILTER (WHERE n_chars >= 1000)").alias("large"))


@query("lang:s p10:d median:d p90:d", "SELECT lang, quantile_cont(n_chars, 0.1) AS p10, median(n_chars) AS median, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY 1")
def agg_percentile(s, d):
    return T(s, d, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.1).alias("p10"), F.median("n_chars").alias("median"), F.percentile("n_chars", 0.9).alias("p90"))


@query("exact:l sketched:l close:b")
def agg_approx_distinct(s, d):
    t = seg.doc_lines(s, d).select(F.explode(N.tokens(F.col("code"))).alias("t"))
    a = t.agg(F.count_distinct("t").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("t", F.lit(14))).alias("sketched"))
    return a.withColumn("close", F.abs(F.col("exact") - F.col("sketched")) <= 0.05 * F.col("exact"))


@query("item:s count:l")
def agg_topk_approx(s, d):
    return lines(s, d).agg(F.expr("approx_top_k(h, 10, 10000)").alias("k")).select(F.explode("k").alias("x")).select("x.item", "x.count")


_ROLL = W("SELECT lang, repo, count(*) AS cells, avg(CASE WHEN is_clone THEN 1.0 ELSE 0.0 END) AS ratio FROM flags GROUP BY {}", "flags")


@query("lang:s repo:s cells:l ratio:d", _ROLL.replace("{}", "ROLLUP (lang, repo)"))
def agg_rollup(s, d):
    return cmw.flags(lines(s, d)).rollup("lang", "repo").agg(F.count("*").alias("cells"), F.avg(F.col("is_clone").cast("double")).alias("ratio"))


@query("lang:s quality:l toxic:l docs:l", "SELECT lang, coalesce(quality, -1) AS quality, coalesce(toxic, -1) AS toxic, count(*) AS docs FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (lang, quality, toxic)")
def agg_cube(s, d):
    return T(s, d, "documents").join(T(s, d, "labels"), "doc_id").cube("lang", "quality", "toxic").agg(F.count("*").alias("docs")).na.fill(-1, ["quality", "toxic"])


@query("lang:s source:s docs:l", "SELECT lang, source, count(*) AS docs FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(s, d):
    return s.sql("SELECT lang, source, count(*) AS docs FROM {t} GROUP BY GROUPING SETS ((lang), (source), ())", t=T(s, d, "documents"))


@query("source:s en:l fr:l de:l es:l", "SELECT source, count_if(lang = 'en') AS en, count_if(lang = 'fr') AS fr, count_if(lang = 'de') AS de, count_if(lang = 'es') AS es FROM documents GROUP BY 1")
def pivot_lang(s, d):
    return T(s, d, "documents").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).count().na.fill(0)


@query("lang:s stat:s v:d", "SELECT lang, unnest(['lo', 'mean', 'hi']) AS stat, unnest([min(n_chars)::DOUBLE, avg(n_chars), max(n_chars)::DOUBLE]) AS v FROM documents GROUP BY lang")
def unpivot_stats(s, d):
    c = F.col("n_chars").cast("double")
    return T(s, d, "documents").groupBy("lang").agg(F.min(c).alias("lo"), F.avg(c).alias("mean"), F.max(c).alias("hi")).unpivot("lang", ["lo", "mean", "hi"], "stat", "v")


# --- windows, sorting, sets ------------------------------------------------
def _by_lang():
    return Wd.partitionBy("lang").orderBy("n_chars", "doc_id")


@query("doc_id:l rn:l rk:l dr:l pr:d cd:d", "SELECT doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, percent_rank() OVER v AS pr, cume_dist() OVER v AS cd FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id), v AS (PARTITION BY lang ORDER BY n_chars)")
def win_rank(s, d):
    v = Wd.partitionBy("lang").orderBy("n_chars")
    return T(s, d, "documents").select("doc_id", F.row_number().over(_by_lang()).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.percent_rank().over(v).alias("pr"), F.cume_dist().over(v).alias("cd"))


@query("event_id:l gap:l", "SELECT event_id, coalesce(epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS gap FROM events")
def win_lag(s, d):
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    return T(s, d, "events").select("event_id", F.coalesce(t - F.lag(t).over(Wd.partitionBy("user_id").orderBy("ts", "event_id")), F.lit(-1)).alias("gap"))


@query("bin:l cnt:l upto:l", W("SELECT size AS bin, cnt, sum(cnt) OVER (ORDER BY size) AS upto FROM (SELECT size, count(*) AS cnt FROM groups GROUP BY 1)", "groups"))
def win_running(s, d):
    h = lines(s, d).groupBy("h").agg(F.count("*").alias("bin")).groupBy("bin").agg(F.count("*").alias("cnt"))
    return h.withColumn("upto", F.sum("cnt").over(Wd.orderBy("bin").rowsBetween(Wd.unboundedPreceding, 0)))


@query("event_id:l recent:l", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS recent FROM events")
def win_range_frame(s, d):
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    return T(s, d, "events").withColumn("t", t).withColumn("recent", F.count("*").over(Wd.partitionBy("user_id").orderBy("t").rangeBetween(-3_600_000_000, 0)))


@query("doc_id:l tile:l", "SELECT doc_id, ntile(10) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS tile FROM documents")
def win_ntile(s, d):
    return T(s, d, "documents").withColumn("tile", F.ntile(10).over(_by_lang()))


_FULL = "OVER (PARTITION BY lang ORDER BY n_chars, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


@query("doc_id:l a:s b:s", f"SELECT doc_id, first_value(source) {_FULL} AS a, last_value(source) {_FULL} AS b FROM documents")
def win_first_last(s, d):
    w = _by_lang().rowsBetween(Wd.unboundedPreceding, Wd.unboundedFollowing)
    return T(s, d, "documents").select("doc_id", F.first("source").over(w).alias("a"), F.last("source").over(w).alias("b"))


@query("doc_id:l third:s", f"SELECT doc_id, nth_value(source, 3) {_FULL} AS third FROM documents")
def win_nth(s, d):
    return T(s, d, "documents").withColumn("third", F.nth_value("source", 3).over(_by_lang().rowsBetween(Wd.unboundedPreceding, Wd.unboundedFollowing)))


def sized(s, d):
    return lines(s, d).groupBy("h").agg(F.count("*").alias("size"))


_SIZED = "(SELECT h, count(*) AS size FROM ne GROUP BY h)"


@query("h:s size:l", W(f"SELECT * FROM {_SIZED}", "ne"))
def sort_global(s, d):
    return sized(s, d).orderBy(F.desc("size"), "h")


@query("h:s size:l", W(f"SELECT * FROM {_SIZED} ORDER BY size DESC, h LIMIT 10", "ne"))
def topk(s, d):
    return sized(s, d).orderBy(F.desc("size"), "h").limit(10)


@query("lang:s h:s size:l", W("SELECT lang, h, size FROM (SELECT lang, h, count(*) AS size, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, h) AS k FROM ne GROUP BY 1, 2) WHERE k <= 3", "ne"))
def limit_per_group(s, d):
    g = lines(s, d).groupBy("lang", "h").agg(F.count("*").alias("size"))
    return g.withColumn("k", F.row_number().over(Wd.partitionBy("lang").orderBy(F.desc("size"), "h"))).where("k <= 3")


@query("h:s size:l", W(f"SELECT * FROM {_SIZED} ORDER BY size DESC, h LIMIT 10 OFFSET 20", "ne"))
def limit_offset(s, d):
    return sized(s, d).orderBy(F.desc("size"), "h").offset(20).limit(10)


for _name, _sql, _op in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", lambda a, b: a.union(b)), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("set_except", "EXCEPT", lambda a, b: a.subtract(b)), ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    query("h:s", W(f"SELECT h FROM ne WHERE repo = 'src0' {_sql} SELECT h FROM ne WHERE repo = 'src1'", "ne"), name=_name)(lambda s, d, op=_op: op(lines(s, d).where("repo = 'src0'").select("h"), lines(s, d).where("repo = 'src1'").select("h")))


# --- functions -------------------------------------------------------------
@query("p_partkey:l a:s b:l c:s e:s f:s g:l", "SELECT p_partkey, upper(trim(p_name)) AS a, length(p_name) AS b, substring(p_name, 2, 4) AS c, split_part(p_name, ' ', 1) AS e, lpad(CAST(p_size AS VARCHAR), 5, '0') AS f, levenshtein(p_name, p_brand) AS g FROM part")
def fn_string(s, d):
    return T(s, d, "part").select("p_partkey", F.upper(F.trim("p_name")).alias("a"), F.length("p_name").alias("b"), F.substring("p_name", 2, 4).alias("c"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("e"), F.lpad(F.col("p_size").cast("string"), 5, "0").alias("f"), F.levenshtein("p_name", "p_brand").alias("g"))


@query("page_id:l title:s links:l", "SELECT page_id, regexp_extract(html, '<h1[^>]*>([^<]*)<', 1) AS title, len(regexp_extract_all(html, '<p')) AS links FROM pages")
def fn_regex(s, d):
    return T(s, d, "pages").select("page_id", F.regexp_extract("html", "<h1[^>]*>([^<]*)<", 1).alias("title"), F.regexp_count("html", F.lit("<p")).alias("links"))


@query("doc_id:l m:s h:s", "SELECT doc_id, md5(text) AS m, sha256(text) AS h FROM documents")
def fn_hash(s, d):
    return T(s, d, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("h"))


@query("page_id:l host:s path:s", "SELECT page_id, regexp_extract(url, '^[A-Za-z]+://([^/?#:]+)', 1) AS host, regexp_extract(url, '^[A-Za-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages")
def fn_url(s, d):
    return T(s, d, "pages").select("page_id", F.try_parse_url("url", F.lit("HOST")).alias("host"), F.try_parse_url("url", F.lit("PATH")).alias("path"))


@query("o_orderkey:l y:l m:l dow:l days:l", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofweek(o_orderdate) + 1 AS dow, date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def fn_date(s, d):
    t = F.col("o_orderdate")
    return T(s, d, "orders").select("o_orderkey", F.year(t).alias("y"), F.month(t).alias("m"), F.dayofweek(t).alias("dow"), F.datediff(t, F.lit("1990-01-01").cast("date")).alias("days"))


@query("l_orderkey:l a:d b:l c:l e:d f:d", "SELECT l_orderkey, l_extendedprice * (1 - l_discount) AS a, floor(l_quantity) AS b, ceil(l_tax * 100) AS c, sqrt(l_quantity) AS e, ln(l_extendedprice) AS f FROM lineitem")
def fn_math(s, d):
    return T(s, d, "lineitem").select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("a"), F.floor("l_quantity").alias("b"), F.ceil(F.col("l_tax") * 100).alias("c"), F.sqrt("l_quantity").alias("e"), F.log("l_extendedprice").alias("f"))


@query("vec_id:l n:l pos:l norm:d", "SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x > 0)) AS pos, sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))) AS norm FROM embeddings")
def fn_array(s, d):
    v = F.col("embedding")
    return T(s, d, "embeddings").select("vec_id", F.size(v).alias("n"), F.size(F.filter(v, lambda x: x > 0)).alias("pos"), F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))).alias("norm"))


@query("nb_id:l pos:l tok:s n:l", W(r"SELECT nb_id, pos, t AS tok, count(*) AS n FROM (SELECT nb_id, pos, unnest(list_filter(regexp_split_to_array(code, '[^\p{L}\p{N}_]+'), lambda t: t <> '')) AS t FROM cells) GROUP BY ALL HAVING count(*) > 1", "cells"))
def fn_map(s, d):
    """Token bags as maps, entries of two and more kept."""
    toks = N.tokens(F.col("code"))
    bag = F.map_from_entries(F.transform(F.array_distinct(toks), lambda t: F.struct(t, F.size(F.filter(toks, lambda u: u == t)))))
    return seg.doc_lines(s, d).select("nb_id", "pos", F.explode(F.map_filter(bag, lambda k, v: v > 1)).alias("tok", "n"))


@query("event_id:l k:s", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def fn_json(s, d):
    return T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("event_id:l a:d b:s", "SELECT event_id, value / nullif(user_id % 3, 0) AS a, CASE WHEN value > 50 THEN 'high' WHEN value IS NULL THEN 'none' ELSE 'low' END AS b FROM events")
def fn_null_cond(s, d):
    v = F.col("value")
    return T(s, d, "events").select("event_id", F.try_divide(v, F.col("user_id") % 3).alias("a"), F.when(v > 50, "high").when(v.isNull(), "none").otherwise("low").alias("b"))


# --- SQL surface -----------------------------------------------------------
def _sql(name, spec, text):
    def run(s, d):
        for t in ("documents", "labels", "orders", "lineitem"):
            T(s, d, t).createOrReplaceTempView(t)
        return s.sql(text)

    query(spec, text, name=name)(run)


_sql("subquery_scalar", "doc_id:l", "SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
_sql("subquery_exists", "o_orderkey:l", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)")
_sql("subquery_in", "doc_id:l", "SELECT doc_id FROM labels WHERE doc_id IN (SELECT doc_id FROM documents WHERE lang = 'en')")
_sql("cte_chain", "clones:l uniques:l", "WITH f AS (SELECT md5(text) AS h FROM documents), g AS (SELECT h, count(*) AS s FROM f GROUP BY h) SELECT sum(CASE WHEN s > 1 THEN s ELSE 0 END) AS clones, sum(CASE WHEN s = 1 THEN 1 ELSE 0 END) AS uniques FROM g")


@query("h:s size:l", W("SELECT h, count(*) AS size FROM ne GROUP BY h HAVING count(*) > 1", "ne"))
def sql_surface(s, d):
    """The method from SQL: a view of cells and SQL functions for the normal form and its hash."""
    seg.doc_lines(s, d).createOrReplaceTempView("cells")
    s.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION strip_ws(code STRING) RETURNS STRING RETURN regexp_replace(code, '[ \\t\\n\\r\\f\\x0B]+', '')")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION cmw_hash(code STRING) RETURNS STRING RETURN md5(regexp_replace(code, '[ \\\\t\\\\n\\\\r\\\\f\\\\x0B]+', ''))")
    return s.sql("SELECT cmw_hash(code) AS h, count(*) AS size FROM cells WHERE strip_ws(code) <> '' GROUP BY 1 HAVING count(*) > 1")


@query("repo:s same:b")
def udaf_bag_union(s, d):
    """Grouped-aggregate pandas UDF over a repository's cell sizes against the native sum."""
    @F.pandas_udf("long")
    def total(v: pd.Series) -> int:
        return int(v.sum())

    t = seg.doc_lines(s, d).select("repo", F.size(N.tokens(F.col("code"))).cast("long").alias("n"))
    return t.groupBy("repo").agg(total("n").alias("a")).join(t.groupBy("repo").agg(F.sum("n").alias("b")), "repo").select("repo", (F.col("a") == F.col("b")).alias("same"))


@query("doc_id:l pos:l code:s", W("SELECT nb_id AS doc_id, pos, code FROM cells", "cells", cells=BLOCK_CELLS))
def udtf_segment(s, d):
    """A Python table function beside ``doc_blocks``: per-row Python, for irregular segmenters only."""

    @F.udtf(returnType="pos int, code string")
    class Segment:
        def eval(self, text: str, k: int):
            parts = text.split("\n")
            for i in range(0, len(parts), k):
                yield i // k, "\n".join(parts[i : i + k])

    s.udtf.register("segment_lines", Segment)
    T(s, d, "documents").createOrReplaceTempView("documents")
    return s.sql("SELECT doc_id, pos, code FROM documents, LATERAL segment_lines(text, 3)")


@query("page_id:l bodies:l same:b")
def map_in_pandas_parse(s, d):
    """Irregular markup by a Python parser in Arrow batches, held against the regular-expression path."""
    import re

    def parse(batches):
        body = re.compile(r"<(?:p|li|h1)[^>]*>([^<]*)<")
        for b in batches:
            yield b.assign(bodies=[len(body.findall(h or "")) for h in b["html"]])[["page_id", "bodies", "native"]]

    native = F.size(F.regexp_extract_all("html", F.lit(r"<(?:p|li|h1)[^>]*>([^<]*)<"), F.lit(1))).cast("long")
    out = T(s, d, "pages").select("page_id", "html", native.alias("native")).mapInPandas(parse, "page_id long, bodies long, native long")
    return out.select("page_id", "bodies", (F.col("bodies") == F.col("native")).alias("same"))
