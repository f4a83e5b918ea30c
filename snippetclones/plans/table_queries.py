"""The clone workloads on the other tables: pages by host, orders by market segment, blocks, event sessions, benchmark templates."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import cmw, connections as C, distributions as D, frequency as Q, review as R, stats as S
from ..operators.components import cut
from ..sources import segment as seg
from .clone_queries import _KW, _RS, _TOTAL, _TOTALS
from .registry import query
from .sqltext import BENCH_CELLS, BLOCK_CELLS, ORDER_CELLS, ORDER_NBS, PAGE_CELLS, PAGE_NBS, SESSION_CELLS, SUMMARY_SPEC, TEMPLATED_CELLS, p_chi2, p_normal, signed_sql, summary, with_ as W

# --- pages: hosts are repositories -----------------------------------------
PAGES = {"cells": PAGE_CELLS, "nbs": PAGE_NBS}


def page_counts(s, d):
    return cmw.counts(cmw.non_empty(seg.page_blocks(s, d)))


def page_conn(s, d):
    n = cut(page_counts(s, d))
    return C.inter_mean(C.per_notebook(seg.page_notebooks(s, d), n), C.partners(n))


@query("nb_id:l edge:l norm:d c0:l sc:l m:l ic:d", W("SELECT * FROM conn", "conn", **PAGES))
def conn_pages(s, d):
    return page_conn(s, d)


@query(SUMMARY_SPEC, W(" UNION ALL ".join(summary(c, "conn") for c in ("edge", "norm", "c0", "ic")), "conn", **PAGES))
def conn_summary_pages(s, d):
    return S.summary8(page_conn(s, d), ["edge", "norm", "c0", "ic"])


@query("bin:l cnt:l", W("SELECT floor(log2(edge + 1)) AS bin, count(*) AS cnt FROM conn GROUP BY 1", "conn", **PAGES))
def conn_hist_pages(s, d):
    return D.hist(page_conn(s, d), "edge", log2=True)


@query("n:l v:d statistic:d p:d", W(f"SELECT *, {p_normal('statistic')} AS p FROM ({signed_sql('conn', 'c0', 'ic')}) q", "conn", **PAGES))
def signed_rank_c0_ic_pages(s, d):
    return S.signed_rank(page_conn(s, d), "c0", "ic")


@query("n:l v:d statistic:d p:d", W(f"SELECT *, {p_normal('statistic')} AS p FROM ({signed_sql('conn', 'c0', 'sc')}) q", "conn", **PAGES))
def signed_rank_c0_sc_pages(s, d):
    return S.signed_rank(page_conn(s, d), "c0", "sc")


@query("x:l y:l cnt:l", W("SELECT floor(log2(c0 + 1)) AS x, floor(log2(ic + 1)) AS y, count(*) AS cnt FROM conn GROUP BY 1, 2", "conn", **PAGES))
def intra_vs_inter_grid_pages(s, d):
    return D.grid2d(page_conn(s, d), F.floor(F.log2(F.col("c0") + 1)), F.floor(F.log2(F.col("ic") + 1)))


@query("nb_id:l other:s c:l is_own:b", W("SELECT nb_id, other, c, repo = other AS is_own FROM (SELECT nb_id, repo, other, count(*) AS c, row_number() OVER (PARTITION BY nb_id ORDER BY count(*) DESC, other) AS k FROM ends GROUP BY 1, 2, 3) WHERE k = 1", "ends", **PAGES))
def top_partner_host(s, d):
    return C.strongest(C.per_repository(page_counts(s, d)))


@query("lang:s pages:l share:d", W("SELECT lang, count(*) AS pages, count(*) / sum(count(*)) OVER () AS share FROM nbs GROUP BY lang", "nbs", **PAGES))
def lang_distribution_pages(s, d):
    pages = seg.page_notebooks(s, d)
    total = pages.agg(F.count("*").alias("total"))  # one row
    return pages.groupBy("lang").agg(F.count("*").alias("pages")).crossJoin(total).withColumn("share", F.col("pages") / F.col("total"))


# --- totals, empties and self-cloning --------------------------------------
_EMPTY = r"SELECT count(*) AS cells, count_if(n = '') AS empties FROM hc"
_SELF = "SELECT count(DISTINCT nb_id) AS self_cloning FROM counts WHERE n >= 2"
for _key, _cells, _make in (("pages", PAGE_CELLS, seg.page_blocks), ("orders", ORDER_CELLS, seg.order_lines), ("sessions", SESSION_CELLS, seg.event_sessions)):
    query("cells:l empties:l", W(_EMPTY, "hc", cells=_cells), name=f"cmw_empty_count_{_key}")(lambda s, d, m=_make: m(s, d).agg(F.count("*").alias("cells"), F.count_if(~F.col("code").rlike(r"[^ \t\n\r\f\x0B]")).alias("empties")))
    query("self_cloning:l", W(_SELF, "counts", cells=_cells), name=f"cmw_self_cloning_{_key}")(lambda s, d, m=_make: cmw.self_clones(cmw.non_empty(m(s, d))).agg(F.count("*").alias("self_cloning")))
query(_TOTAL, W(_TOTALS, "groups", cells=SESSION_CELLS), name="cmw_totals_sessions")(lambda s, d: cmw.totals(cmw.non_empty(seg.event_sessions(s, d))))


@query("bin:l cnt:l", W("SELECT size AS bin, count(*) AS cnt FROM (SELECT count(*) AS size FROM fps GROUP BY fp HAVING count(*) >= 2) GROUP BY 1", "fps", cells=ORDER_CELLS))
def notebook_clone_hist_orders(s, d):
    return D.hist(cmw.notebook_clones(cmw.notebook_fingerprints(seg.order_lines(s, d))), "size")


# --- blocks: lines of code of clones ---------------------------------------
def block_groups(s, d):
    return cmw.groups(cmw.non_empty(seg.doc_blocks(s, d)))


@query(SUMMARY_SPEC, W(f"{summary('median_loc', 'flags WHERE is_clone', 'clones')} UNION ALL {summary('median_loc', 'groups WHERE size >= 2', 'groups')}", "flags", cells=BLOCK_CELLS))
def cmw_loc_summary_blocks(s, d):
    g = block_groups(s, d).where("size >= 2")
    return S.summary8(g, ["median_loc"], weight="size").withColumn("measure", F.lit("clones")).union(S.summary8(g, ["median_loc"]).withColumn("measure", F.lit("groups")))


@query("bin:l cells:l groups:l", W("SELECT median_loc AS bin, sum(size) AS cells, count(*) AS groups FROM groups WHERE size >= 2 GROUP BY 1", "groups", cells=BLOCK_CELLS))
def cmw_loc_hist_blocks(s, d):
    return block_groups(s, d).where("size >= 2").groupBy(F.col("median_loc").alias("bin")).agg(F.sum("size").alias("cells"), F.count("*").alias("groups"))


@query("h:s size:l median_loc:l sample:s", W("SELECT * FROM groups WHERE size >= 2 ORDER BY size DESC, h LIMIT 10", "groups", cells=BLOCK_CELLS))
def top_clones_blocks(s, d):
    return R.top(block_groups(s, d), 10)


@query("h:s size:l median_loc:l sample:s", W("SELECT * FROM groups WHERE size >= 2 AND median_loc <= 1 ORDER BY size DESC, h LIMIT 10", "groups"))
def top_clones_single_line(s, d):
    return R.top(cmw.groups(cmw.non_empty(seg.doc_lines(s, d))), 10, max_loc=1)


# --- orders: market segments are languages ---------------------------------
ORDERS = {"cells": ORDER_CELLS, "nbs": ORDER_NBS}


def order_freq(s, d):
    return Q.per_notebook(seg.order_notebooks(s, d), cmw.flags(cmw.non_empty(seg.order_lines(s, d))))


@query(SUMMARY_SPEC, W(summary("freq", "freq"), "freq", **ORDERS))
def clone_frequency_summary_orders(s, d):
    return S.summary8(order_freq(s, d), ["freq"])


@query("k:l n:l statistic:d df:l p:d", W(f"SELECT *, {p_chi2('statistic', 'df')} AS p FROM ({_KW}) q", "freq", **ORDERS))
def kruskal_wallis_orders(s, d):
    return S.kruskal(order_freq(s, d), "lang", "freq")


_FAMILY = f"SELECT *, {p_normal('statistic')} AS p FROM ({_RS}) q"


@query("g1:s g2:s n1:l n2:l w:d statistic:d p:d adjusted:d grade:s", W("SELECT *, CASE WHEN adjusted < 0.001 THEN '***' WHEN adjusted < 0.01 THEN '**' WHEN adjusted < 0.05 THEN '*' ELSE '' END AS grade FROM (SELECT *, least(1.0, min(p * i) OVER (ORDER BY i)) AS adjusted FROM (SELECT *, row_number() OVER (ORDER BY p DESC) AS i FROM fam))", "freq", fam=_FAMILY, **ORDERS))
def segment_posthoc(s, d):
    return S.grade(S.adjust(S.pairwise_ranksum(order_freq(s, d), "lang", "freq")))


# --- benchmark: templates that recur in documents --------------------------
def _templates(s, d):
    return cmw.non_empty(seg.benchmark_lines(s, d))


@query("h:s size:l median_loc:l sample:s", W("SELECT * FROM groups WHERE size >= 2 ORDER BY size DESC, h LIMIT 10", "groups", cells=TEMPLATED_CELLS))
def top_clones_benchmark(s, d):
    return R.top(cmw.groups(cmw.non_empty(seg.doc_lines(s, d).union(seg.benchmark_lines(s, d)))), 10)


_BN = r"SELECT nb_id, pos, md5(regexp_replace(code, '[ \t\n\r\f\x0B]+', '', 'g')) AS h FROM bcells WHERE regexp_replace(code, '[ \t\n\r\f\x0B]+', '', 'g') <> ''"
_BCELLS = BENCH_CELLS.split("AS (", 1)[1].rsplit(")", 1)[0]


@query("item_id:l cells:l found:l documents:l", W("SELECT -b.nb_id - 1 AS item_id, count(DISTINCT b.pos) AS cells, count(DISTINCT CASE WHEN c.h IS NOT NULL THEN b.pos END) AS found, count(DISTINCT c.nb_id) AS documents FROM bn b LEFT JOIN counts c ON c.h = b.h GROUP BY 1", "counts", bcells=_BCELLS, bn=_BN))
def template_uses(s, d):
    return R.template_uses(_templates(s, d), cmw.counts(cmw.non_empty(seg.doc_lines(s, d)))).select((-F.col("nb_id") - 1).alias("item_id"), "cells", "found", "documents")


@query("nb_id:l pos:l", W("SELECT nb_id, pos FROM ne WHERE h NOT IN (SELECT h FROM bn)", "ne", bcells=_BCELLS, bn=_BN))
def corpus_without_templates(s, d):
    return cmw.non_empty(seg.doc_lines(s, d)).join(_templates(s, d).select("h").distinct(), "h", "left_anti")


_DEVIATED = """SELECT DISTINCT c.nb_id FROM counts c JOIN counts t ON c.h = t.h AND c.nb_id > t.nb_id JOIN tpl ON tpl.nb_id = t.nb_id JOIN (SELECT nb_id, sum(n) AS own FROM counts GROUP BY 1) o ON o.nb_id = c.nb_id
GROUP BY c.nb_id, t.nb_id, o.own HAVING sum(c.n) >= 0.8 * o.own"""


@query("nb_id:l", W("SELECT nb_id FROM nbs WHERE nb_id NOT IN (SELECT nb_id FROM dev)", "counts", "fps", "nbs", tpl="SELECT min(nb_id) AS nb_id FROM fps GROUP BY fp HAVING count(*) >= 2", dev=_DEVIATED))
def dedup_template_corpus(s, d):
    """The corpus that is left when notebooks that deviate little from a template go."""
    c = cmw.counts(cmw.non_empty(seg.doc_lines(s, d)))
    t = cmw.notebook_clones(cmw.notebook_fingerprints(seg.doc_lines(s, d))).select(F.col("first_nb").alias("template"))
    return seg.notebooks(s, d).join(R.deviated(c, t, 0.8).select("nb_id").distinct(), "nb_id", "left_anti")
