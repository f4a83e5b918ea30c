"""Registered queries of the exact-clone analysis: groups, flags, frequencies, tests, connections, review, dedup."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import normalize as N
from ..operators import cmw, connections as C, distributions as D, frequency as Q, review as R, stats as S
from ..operators.components import cut
from ..sources import segment as seg
from .registry import query
from .sqltext import BLOCK_CELLS, ORDER_CELLS, PAGE_CELLS, SUMMARY_SPEC, TURN_CELLS, WHOLE_CELLS, p_chi2, p_normal, p_t, signed_sql, spearman_sql, summary, with_

W = with_


def lines(s, d):
    return cmw.non_empty(seg.doc_lines(s, d))


def freq(s, d):
    return Q.per_notebook(seg.notebooks(s, d), cmw.flags(lines(s, d)))


def conn(s, d):
    return C.per_notebook(seg.notebooks(s, d), cmw.counts(lines(s, d)))


def full_conn(s, d):
    n = cut(cmw.counts(lines(s, d)))  # read with different columns by sizes, holders and partners: one scan of the texts instead of one each
    return C.inter_mean(C.per_notebook(seg.notebooks(s, d), n), C.partners(n))


# --- exact clones ----------------------------------------------------------
@query("nb_id:l pos:l n:s", W("SELECT nb_id, pos, n FROM hc", "hc"))
def cmw_normalise(s, d):
    return cmw.hashed(seg.doc_lines(s, d))


@query("nb_id:l pos:l h:s", W("SELECT nb_id, pos, h FROM hc", "hc"))
def cmw_fingerprint(s, d):
    return cmw.hashed(seg.doc_lines(s, d))


@query("fingerprints:l collisions:l", W("SELECT count(*) AS fingerprints, count_if(k > 1) AS collisions FROM (SELECT h, count(DISTINCT n) AS k FROM ne GROUP BY h)", "ne"))
def cmw_collision_audit(s, d):
    return lines(s, d).groupBy("h").agg(F.min("n").alias("a"), F.max("n").alias("b")).agg(F.count("*").alias("fingerprints"), F.count_if(F.col("a") != F.col("b")).alias("collisions"))


def blanked(s, d):
    return seg.doc_lines(s, d).withColumn("code", F.when(F.col("pos") % 13 == 4, F.lit(" \t ")).otherwise(F.col("code")))


_BLANK = "SELECT * REPLACE (CASE WHEN pos % 13 = 4 THEN ' ' || chr(9) || ' ' ELSE code END AS code) FROM cells"


@query("cells:l empties:l share:d", W(r"SELECT count(*) AS cells, count_if(regexp_replace(code, '[ \t\n\r\f\x0B]+', '', 'g') = '') AS empties, avg(CASE WHEN regexp_replace(code, '[ \t\n\r\f\x0B]+', '', 'g') = '' THEN 1.0 ELSE 0.0 END) AS share FROM blank", "cells", blank=_BLANK))
def cmw_empty_count(s, d):
    e = N.strip_ws(F.col("code")) == ""
    return blanked(s, d).agg(F.count("*").alias("cells"), F.count_if(e).alias("empties"), F.avg(e.cast("double")).alias("share"))


_GROUP = "h:s size:l n_nb:l n_repo:l median_loc:l sample:s"


@query(_GROUP, W("SELECT * FROM groups", "groups"))
def cmw_groups(s, d):
    return cmw.groups(lines(s, d))


@query(_GROUP, W("SELECT * FROM groups", "groups", cells=BLOCK_CELLS))
def cmw_groups_blocks(s, d):
    return cmw.groups(cmw.non_empty(seg.doc_blocks(s, d)))


@query(_GROUP, W("SELECT * FROM groups", "groups", cells=PAGE_CELLS))
def cmw_groups_pages(s, d):
    return cmw.groups(cmw.non_empty(seg.page_blocks(s, d)))


@query("nb_id:l pos:l h:s size:l is_clone:b", W("SELECT * FROM flags", "flags"))
def cmw_flags(s, d):
    return cmw.flags(lines(s, d))


@query("nb_id:l pos:l h:s size:l is_clone:b", W("SELECT * FROM flags", "flags"))
def cmw_flags_window(s, d):
    return cmw.flags(lines(s, d), "window")


_TOTAL = "clones:l groups:l uniques:l ratio:d"
_TOTALS = "SELECT sum(CASE WHEN size > 1 THEN size ELSE 0 END) AS clones, count_if(size > 1) AS groups, count_if(size = 1) AS uniques, sum(CASE WHEN size > 1 THEN size ELSE 0 END) / sum(size) AS ratio FROM groups"


def _totals(name, cells_sql, make):
    query(_TOTAL, W(_TOTALS, "groups", cells=cells_sql), name=name)(lambda s, d: cmw.totals(cmw.non_empty(make(s, d))))


for _name, _sql, _make in (("cmw_totals", W("", "cells").split("WITH ", 1)[1].strip(), seg.doc_lines), ("cmw_totals_pages", PAGE_CELLS, seg.page_blocks), ("cmw_totals_orders", ORDER_CELLS, seg.order_lines), ("cmw_totals_turns", TURN_CELLS, seg.turns), ("cmw_totals_blocks", BLOCK_CELLS, seg.doc_blocks), ("file_level_clones", WHOLE_CELLS, seg.doc_whole)):
    _totals(_name, _sql, _make)


@query("several:l single:l", W("SELECT count_if(n_nb >= 2) AS several, count_if(n_nb = 1) AS single FROM groups WHERE size >= 2", "groups"))
def cmw_in_two_notebooks(s, d):
    return cmw.groups(lines(s, d)).where("size >= 2").agg(F.count_if(F.col("n_nb") >= 2).alias("several"), F.count_if(F.col("n_nb") == 1).alias("single"))


@query("nb_id:l", W("SELECT DISTINCT nb_id FROM counts WHERE n >= 2", "counts"))
def cmw_self_cloning(s, d):
    return cmw.self_clones(lines(s, d))


@query("notebooks:l self_cloning:l share:d", W("SELECT count(*) AS notebooks, count(c.nb_id) AS self_cloning, count(c.nb_id) / count(*) AS share FROM nbs LEFT JOIN (SELECT DISTINCT nb_id FROM counts WHERE n >= 2) c USING (nb_id)", "counts", "nbs"))
def cmw_self_cloning_share(s, d):
    own = cmw.self_clones(lines(s, d)).withColumn("own", F.lit(1))
    return seg.notebooks(s, d).join(own, "nb_id", "left").agg(F.count("*").alias("notebooks"), F.count("own").alias("self_cloning")).withColumn("share", F.col("self_cloning") / F.col("notebooks"))


@query("bin:l cnt:l", W("SELECT size AS bin, count(*) AS cnt FROM groups GROUP BY 1", "groups"))
def cmw_group_size_hist(s, d):
    return D.hist(lines(s, d).groupBy("h").agg(F.count("*").alias("size")), "size")


@query("bin:l cnt:l", W("SELECT size AS bin, count(*) AS cnt FROM groups GROUP BY 1", "groups", cells=ORDER_CELLS))
def cmw_group_size_hist_orders(s, d):
    return D.hist(cmw.non_empty(seg.order_lines(s, d)).groupBy("h").agg(F.count("*").alias("size")), "size")


@query("share:d", W("SELECT sum(CASE WHEN size < 200 THEN size ELSE 0 END) / sum(size) AS share FROM groups", "groups"))
def cmw_below_200_share(s, d):
    g = lines(s, d).groupBy("h").agg(F.count("*").alias("size"))
    return g.agg((F.sum(F.when(F.col("size") < 200, F.col("size")).otherwise(0)) / F.sum("size")).alias("share"))


@query("bin:l cnt:l", W("SELECT median_loc AS bin, sum(size) AS cnt FROM groups WHERE size >= 2 GROUP BY 1", "groups"))
def cmw_clone_loc_hist(s, d):
    return D.hist(cmw.groups(lines(s, d)).where("size >= 2"), "median_loc", weight="size")


@query("bin:l cnt:l", W("SELECT median_loc AS bin, count(*) AS cnt FROM groups WHERE size >= 2 GROUP BY 1", "groups"))
def cmw_group_loc_hist(s, d):
    return D.hist(cmw.groups(lines(s, d)).where("size >= 2"), "median_loc")


@query(SUMMARY_SPEC, W(f"{summary('median_loc', 'flags WHERE is_clone', 'clones')} UNION ALL {summary('median_loc', 'groups WHERE size >= 2', 'groups')}", "flags"))
def cmw_loc_summary(s, d):
    g = cmw.groups(lines(s, d)).where("size >= 2")
    a = S.summary8(g, ["median_loc"], weight="size").withColumn("measure", F.lit("clones"))
    return a.union(S.summary8(g, ["median_loc"]).withColumn("measure", F.lit("groups")))


@query("loc:l cells:l rate:d", W("SELECT loc, count(*) AS cells, avg(CASE WHEN is_clone THEN 1.0 ELSE 0.0 END) AS rate FROM flags GROUP BY loc", "flags"))
def cmw_small_more_cloned(s, d):
    return cmw.flags(lines(s, d)).groupBy("loc").agg(F.count("*").alias("cells"), F.avg(F.col("is_clone").cast("double")).alias("rate"))


@query("nb_id:l", W("SELECT nb_id FROM freq WHERE cells > 0 AND cloned = cells", "freq"))
def cmw_all_cloned(s, d):
    return freq(s, d).where("cells > 0 AND cloned = cells")


@query("nb_id:l", W("SELECT nb_id FROM freq WHERE cells > 0 AND cloned = 0", "freq"))
def cmw_all_unique(s, d):
    return freq(s, d).where("cells > 0 AND cloned = 0")


@query("notebooks:l all_cloned:l all_unique:l cloned_share:d unique_share:d", W("SELECT count(*) AS notebooks, count_if(cells > 0 AND cloned = cells) AS all_cloned, count_if(cells > 0 AND cloned = 0) AS all_unique, count_if(cells > 0 AND cloned = cells) / count(*) AS cloned_share, count_if(cells > 0 AND cloned = 0) / count(*) AS unique_share FROM freq", "freq"))
def frequency_extremes(s, d):
    return Q.extremes(freq(s, d))


@query("fp:s size:l first_nb:l", W("SELECT fp, count(*) AS size, min(nb_id) AS first_nb FROM fps GROUP BY fp HAVING count(*) >= 2", "fps"))
def notebook_clones(s, d):
    return cmw.notebook_clones(cmw.notebook_fingerprints(seg.doc_lines(s, d)))


@query("bin:l cnt:l", W("SELECT size AS bin, count(*) AS cnt FROM (SELECT count(*) AS size FROM fps GROUP BY fp HAVING count(*) >= 2) GROUP BY 1", "fps"))
def notebook_clone_hist(s, d):
    return D.hist(cmw.notebook_clones(cmw.notebook_fingerprints(seg.doc_lines(s, d))), "size")


@query(_TOTAL, W(_TOTALS, "groups", cells=W("", "cells").split("WITH ", 1)[1].strip().replace("SELECT nb_id, repo, lang, pos, code,", "SELECT nb_id, repo, lang, pos, regexp_replace(code, '#[^\\n]*', '', 'g') AS code,", 1)))
def type1_clones(s, d):
    c = seg.doc_lines(s, d)
    return cmw.totals(cmw.non_empty(c.withColumn("code", N.strip_comments(F.col("code"), block=None))))


@query(_TOTAL, W(_TOTALS, "groups", cells=W("", "cells").split("WITH ", 1)[1].strip().replace("SELECT nb_id, repo, lang, pos, code,", r"SELECT nb_id, repo, lang, pos, regexp_replace(regexp_replace(code, '[0-9]+', '0', 'g'), '[\p{L}_][\p{L}\p{N}_]*', 'W', 'g') AS code,", 1)))
def type2_clones(s, d):
    c = seg.doc_lines(s, d)
    code = F.regexp_replace(F.regexp_replace("code", "[0-9]+", "0"), r"[\p{L}_][\p{L}\p{N}_]*", "W")
    return cmw.totals(cmw.non_empty(c.withColumn("code", code)))


# --- frequencies and tests -------------------------------------------------
@query("nb_id:l cells:l cloned:l freq:d", W("SELECT * FROM freq", "freq"))
def clone_frequency(s, d):
    return freq(s, d)


@query(SUMMARY_SPEC, W(summary("freq", "freq"), "freq"))
def clone_frequency_summary(s, d):
    return S.summary8(freq(s, d), ["freq"])


@query("bin:l cnt:l", W("SELECT least(floor(freq / 0.05), 19) AS bin, count(*) AS cnt FROM freq GROUP BY 1", "freq"))
def clone_frequency_hist(s, d):
    return D.hist(freq(s, d), "freq", width=0.05, cap=19)


@query("x:l y:l cnt:l", W("SELECT cells AS x, least(floor(freq / 0.05), 19) AS y, count(*) AS cnt FROM freq GROUP BY 1, 2", "freq"))
def freq_vs_cells(s, d):
    return D.grid2d(freq(s, d), F.col("cells"), F.least(F.floor(F.col("freq") / 0.05), F.lit(19)))


@query("n:l rho:d statistic:d p:d", W(f"SELECT *, {p_t('statistic', '(n - 2)')} AS p FROM ({spearman_sql('freq', 'cells', 'freq')}) q", "freq"))
def spearman(s, d):
    return S.spearman(freq(s, d), "cells", "freq")


@query("n:l skewness:d", W("SELECT count(*) AS n, sum(r ** 3) / count(*) / (sum(r ** 2) / count(*)) ** 1.5 AS skewness FROM (SELECT freq - avg(freq) OVER (PARTITION BY lang) AS r FROM freq)", "freq"))
def normality_probe(s, d):
    return S.residual_moments(freq(s, d), "lang", "freq")


_ANOVA = "SELECT k, n, ((q - t * t / n) / (k - 1)) / (w / (n - k)) AS statistic, k - 1 AS df1, n - k AS df2 FROM (SELECT count(*) AS k, sum(c) AS n, sum(c * m) AS t, sum(c * m * m) AS q, sum(c * v) AS w FROM (SELECT lang, count(*) AS c, avg(freq) AS m, var_pop(freq) AS v FROM freq GROUP BY lang))"


@query("k:l n:l statistic:d df1:l df2:l", W(_ANOVA, "freq"))
def anova_oneway(s, d):
    return S.anova(freq(s, d), "lang", "freq")


_KW = """SELECT count(*) AS k, sum(c) AS n, (12 / (sum(c) * (sum(c) + 1)) * sum(t * t / c) - 3 * (sum(c) + 1)) / (1 - (SELECT sum(x::DOUBLE ** 3 - x) FROM (SELECT count(*) AS x FROM freq GROUP BY freq)) / (sum(c)::DOUBLE ** 3 - sum(c))) AS statistic, count(*) - 1 AS df
FROM (SELECT lang, count(*)::DOUBLE AS c, sum(r) AS t FROM (SELECT lang, rank() OVER (ORDER BY freq) + (count(*) OVER (PARTITION BY freq) - 1) / 2 AS r FROM freq) GROUP BY lang)"""


@query("k:l n:l statistic:d df:l p:d", W(f"SELECT *, {p_chi2('statistic', 'df')} AS p FROM ({_KW}) q", "freq"))
def kruskal_wallis(s, d):
    return S.kruskal(freq(s, d), "lang", "freq")


@query("lang:s q1:d q2:d q3:d low:d high:d outliers:l", W("""SELECT lang, q1, q2, q3, min(CASE WHEN i THEN freq END) AS low, max(CASE WHEN i THEN freq END) AS high, count_if(NOT i) AS outliers FROM (
  SELECT *, freq BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1) AS i FROM freq JOIN (SELECT lang, quantile_cont(freq, 0.25) AS q1, quantile_cont(freq, 0.5) AS q2, quantile_cont(freq, 0.75) AS q3 FROM freq GROUP BY lang) USING (lang)) GROUP BY ALL""", "freq"))
def lang_boxplot(s, d):
    return D.box(freq(s, d), "lang", "freq")


_RS = """SELECT g1, g2, n1, n2, w, (w - n1 * n2 / 2 - sign(w - n1 * n2 / 2) * 0.5) / nullif(sqrt(n1 * n2 / 12 * (n1 + n2 + 1 - ties / ((n1 + n2) * (n1 + n2 - 1)))), 0) AS statistic FROM (
  SELECT g1, g2, sum(x)::DOUBLE AS n1, sum(t - x)::DOUBLE AS n2, sum(x * r) - sum(x) * (sum(x) + 1) / 2 AS w, sum(t::DOUBLE ** 3 - t) AS ties FROM (
    SELECT g1, g2, v, t, x, sum(t) OVER (PARTITION BY g1, g2 ORDER BY v) - (t - 1) / 2 AS r FROM (
      SELECT p.g1, p.g2, f.freq AS v, count(*) AS t, count_if(f.lang = p.g1) AS x FROM freq f JOIN (SELECT a.lang AS g1, b.lang AS g2 FROM (SELECT DISTINCT lang FROM freq) a JOIN (SELECT DISTINCT lang FROM freq) b ON a.lang < b.lang) p ON f.lang = p.g1 OR f.lang = p.g2 GROUP BY ALL))
  GROUP BY g1, g2)"""


_FAMILY = f"SELECT *, {p_normal('statistic')} AS p FROM ({_RS}) q"


@query("g1:s g2:s n1:l n2:l w:d statistic:d p:d", W("SELECT * FROM fam", "freq", fam=_FAMILY))
def pairwise_ranksum(s, d):
    return S.pairwise_ranksum(freq(s, d), "lang", "freq")


def family(s, d):
    """The tests that are adjusted together: all pairs of languages."""
    return S.pairwise_ranksum(freq(s, d), "lang", "freq")


_HOCH = "SELECT *, least(1.0, min(p * i) OVER (ORDER BY i)) AS adjusted FROM (SELECT *, row_number() OVER (ORDER BY p DESC) AS i FROM fam)"
_GRADED = f"SELECT *, CASE WHEN adjusted < 0.001 THEN '***' WHEN adjusted < 0.01 THEN '**' WHEN adjusted < 0.05 THEN '*' ELSE '' END AS grade FROM ({_HOCH})"


@query("g1:s g2:s p:d adjusted:d", W(_HOCH, "freq", fam=_FAMILY))
def p_hochberg(s, d):
    return S.adjust(family(s, d))


@query("g1:s g2:s p:d adjusted:d", W("SELECT *, least(1.0, p * (SELECT count(*) FROM fam)) AS adjusted FROM fam", "freq", fam=_FAMILY))
def p_bonferroni(s, d):
    return S.adjust(family(s, d), "bonferroni")


@query("g1:s g2:s adjusted:d grade:s", W(_GRADED, "freq", fam=_FAMILY))
def significance_grade(s, d):
    return S.grade(S.adjust(family(s, d)))


@query("g1:s g2:s statistic:d p:d adjusted:d grade:s", W(_GRADED, "freq", fam=_FAMILY))
def language_posthoc(s, d):
    """The whole post-hoc table: rank-sum, p, step-up adjustment and marks."""
    return S.grade(S.adjust(family(s, d)))


@query("statistic:d p:d log10_p:d", W(f"SELECT statistic, p, log10(p) AS log10_p FROM (SELECT *, {p_chi2('statistic', 'df')} AS p FROM ({_KW}) q)", "freq"))
def udf_pandas_pvalue(s, d):
    return S.kruskal(freq(s, d), "lang", "freq")


# --- connections -----------------------------------------------------------
@query("nb_id:l edge:l", W("SELECT * FROM conn", "conn"))
def conn_absolute(s, d):
    return conn(s, d)


@query("nb_id:l edge:l", W("SELECT n.nb_id, coalesce(sum(c.n * (g.size - 1)), 0) AS edge FROM nbs n LEFT JOIN counts c USING (nb_id) LEFT JOIN groups g ON g.h = c.h GROUP BY 1", "groups", "counts", "nbs"))
def conn_absolute_endpoint(s, d):
    return C.per_notebook(seg.notebooks(s, d), cmw.counts(lines(s, d)), "endpoint")


@query("nb_id:l norm:d", W("SELECT * FROM conn", "conn"))
def conn_normalised(s, d):
    return conn(s, d)


@query(SUMMARY_SPEC, W(f"{summary('edge', 'conn')} UNION ALL {summary('norm', 'conn')}", "conn"))
def conn_summary(s, d):
    return S.summary8(conn(s, d), ["edge", "norm"])


@query("measure:s bin:l cnt:l", W("SELECT 'edge' AS measure, floor(log2(edge + 1)) AS bin, count(*) AS cnt FROM conn GROUP BY 2 UNION ALL SELECT 'norm', floor(log2(norm + 1)), count(*) FROM conn GROUP BY 2", "conn"))
def conn_hist(s, d):
    c = conn(s, d)
    return D.hist(c, "edge", log2=True).withColumn("measure", F.lit("edge")).union(D.hist(c, "norm", log2=True).withColumn("measure", F.lit("norm")))


@query("nb_id:l c0:l", W("SELECT * FROM conn", "conn"))
def conn_intra(s, d):
    return conn(s, d)


@query("nb_id:l sc:l", W("SELECT * FROM conn", "conn"))
def conn_inter_total(s, d):
    return conn(s, d)


@query("nb_id:l other:s c:l", W("SELECT nb_id, other, count(*) AS c FROM ends GROUP BY 1, 2", "ends"))
def conn_per_repo(s, d):
    return C.per_repository(cmw.counts(lines(s, d)))


@query("nb_id:l m:l ic:d", W("SELECT * FROM conn", "conn"))
def conn_inter_mean(s, d):
    return full_conn(s, d)


@query("nb_id:l m:l ic:d")
def conn_inter_mean_sketched(s, d):
    n = cmw.counts(lines(s, d))
    return C.inter_mean_sketched(C.per_notebook(seg.notebooks(s, d), n), n)


@query("n:l v:d statistic:d p:d", W(f"SELECT *, {p_normal('statistic')} AS p FROM ({signed_sql('conn', 'c0', 'ic')}) q", "conn"))
def signed_rank_c0_ic(s, d):
    return S.signed_rank(full_conn(s, d), "c0", "ic")


@query("n:l v:d statistic:d p:d", W(f"SELECT *, {p_normal('statistic')} AS p FROM ({signed_sql('conn', 'c0', 'sc')}) q", "conn"))
def signed_rank_c0_sc(s, d):
    return S.signed_rank(conn(s, d), "c0", "sc")


@query("x:l y:l cnt:l above:l below:l", W("SELECT floor(log2(c0 + 1)) AS x, floor(log2(ic + 1)) AS y, count(*) AS cnt, count_if(c0 < ic) AS above, count_if(c0 > ic) AS below FROM conn GROUP BY 1, 2", "conn"))
def intra_vs_inter_grid(s, d):
    return full_conn(s, d).groupBy(F.floor(F.log2(F.col("c0") + 1)).alias("x"), F.floor(F.log2(F.col("ic") + 1)).alias("y")).agg(F.count("*").alias("cnt"), F.count_if(F.col("c0") < F.col("ic")).alias("above"), F.count_if(F.col("c0") > F.col("ic")).alias("below"))


@query("nb_id:l other:s c:l is_own:b", W("SELECT nb_id, other, c, repo = other AS is_own FROM (SELECT nb_id, repo, other, count(*) AS c, row_number() OVER (PARTITION BY nb_id ORDER BY count(*) DESC, other) AS k FROM ends GROUP BY 1, 2, 3) WHERE k = 1", "ends"))
def top_partner_repo(s, d):
    return C.strongest(C.per_repository(cmw.counts(lines(s, d))))


@query("nb_id:l h:s n:l s:l edges:l", W("SELECT c.nb_id, c.h, c.n, g.size AS s, c.n * (g.size - c.n) + c.n * (c.n - 1) // 2 AS edges FROM counts c JOIN groups g USING (h) WHERE c.nb_id = (SELECT nb_id FROM conn ORDER BY edge DESC, nb_id LIMIT 1)", "groups", "counts", "conn"))
def conn_extreme_explain(s, d):
    top = conn(s, d).orderBy(F.desc("edge"), "nb_id").limit(1)
    return C.explain(cmw.counts(lines(s, d)), top)


@query("x:l y:l cnt:l", W("SELECT x, y, count(*) AS cnt FROM edges GROUP BY 1, 2", "edges"))
def conn_edge_list(s, d):
    return C.edge_list(lines(s, d)).groupBy("x", "y").agg(F.count("*").alias("cnt"))


@query("endpoints:l twice_pairs:l", W("SELECT sum(size * (size - 1)) AS endpoints, 2 * (SELECT count(*) FROM edges) AS twice_pairs FROM groups", "groups", "edges"))
def conn_handshake(s, d):
    n = cmw.counts(lines(s, d))
    ends = C.per_notebook(seg.notebooks(s, d), n, "endpoint").agg(F.sum("edge").alias("endpoints"))
    two = n.groupBy("h").agg(F.sum("n").alias("s")).agg(F.sum(F.col("s") * (F.col("s") - 1)).alias("twice_pairs"))
    return ends.crossJoin(two)  # one row each


# --- review, dedup, report -------------------------------------------------
@query("h:s size:l median_loc:l sample:s", W("SELECT * FROM groups WHERE size >= 2 ORDER BY size DESC, h LIMIT 10", "groups"))
def top_clones(s, d):
    return R.top(cmw.groups(lines(s, d)), 10)


@query("h:s size:l median_loc:l sample:s", W("SELECT * FROM groups WHERE size >= 2 AND median_loc >= 4 ORDER BY size DESC, h LIMIT 10", "groups"))
def top_clones_four_lines(s, d):
    return R.top(cmw.groups(lines(s, d)), 10, min_loc=4)


@query("h:s size:l sample:s", W("SELECT * FROM groups WHERE size >= 2 AND len(list_filter(string_split(sample, chr(10)), lambda x: NOT regexp_matches(x, '^(Licensed|This work|The|import) '))) = 0", "groups"))
def header_only_clones(s, d):
    return R.pattern_only(cmw.groups(lines(s, d)).where("size >= 2"), "^(Licensed|This work|The|import) ")


_LIC = (("apache", "Apache License"), ("gnu", "GNU General Public License"), ("cc", "CC BY"), ("mit", "MIT License"))


@query("kind:s cells:l", W(" UNION ALL ".join(f"SELECT '{k}' AS kind, count(*) AS cells FROM ne WHERE contains(code, '{p}')" for k, p in _LIC), "ne"))
def licence_clones(s, d):
    return R.licence(lines(s, d), dict(_LIC))


@query("h:s size:l", W("SELECT h, size FROM groups WHERE size >= 2 AND contains(sample, 'Licensed')", "groups"))
def marker_clones(s, d):
    return R.contains(cmw.groups(lines(s, d)).where("size >= 2"), "Licensed")


@query("fp:s size:l first_nb:l", W("SELECT fp, count(*) AS size, min(nb_id) AS first_nb FROM fps GROUP BY fp HAVING count(*) >= 2 ORDER BY size DESC, fp LIMIT 10", "fps"))
def template_clusters(s, d):
    return cmw.notebook_clones(cmw.notebook_fingerprints(seg.doc_lines(s, d))).orderBy(F.desc("size"), "fp").limit(10)


@query("name:s uses:l", W(r"SELECT t AS name, sum(size) AS uses FROM (SELECT size, unnest(list_filter(regexp_split_to_array(sample, '[^\p{L}\p{N}_]+'), lambda x: x <> '' AND len(x) <= 3)) AS t FROM (SELECT * FROM groups WHERE size >= 2 ORDER BY size DESC, h LIMIT 100)) GROUP BY 1", "groups"))
def naming_frequency(s, d):
    return R.naming(cmw.groups(lines(s, d)), 100)


@query("lib:s alias:s uses:l", W(r"SELECT m[1] AS lib, m[2] AS alias, count(*) AS uses FROM (SELECT [regexp_extract(x, '([\p{L}]+) in ([\p{L}]+)', 1), regexp_extract(x, '([\p{L}]+) in ([\p{L}]+)', 2)] AS m FROM (SELECT unnest(regexp_extract_all(code, '[\p{L}]+ in [\p{L}]+')) AS x FROM cells)) GROUP BY 1, 2", "cells"))
def alias_frequency(s, d):
    return R.alias(seg.doc_lines(s, d), "in")


@query("h:s size:l sample:s", W(r"SELECT * FROM groups WHERE size >= 2 AND len(list_filter(regexp_split_to_array(sample, '[^\p{L}\p{N}_]+'), lambda x: x <> '')) = 1", "groups"))
def single_token_clones(s, d):
    return R.single_token(cmw.groups(lines(s, d)).where("size >= 2"))


@query("h:s score:d", W("SELECT h, n_repo / (1.0 + len(sample)) AS score FROM groups WHERE size >= 2", "groups"))
def accidental_score(s, d):
    return R.accidental(cmw.groups(lines(s, d)).where("size >= 2"))


@query("top_share:d majority:b", W("SELECT max(n_nb) / (SELECT count(*) FROM nbs) AS top_share, max(n_nb) / (SELECT count(*) FROM nbs) > 0.5 AS majority FROM groups", "groups", "nbs"))
def majority_snippet(s, d):
    return R.majority(cmw.groups(lines(s, d)), seg.notebooks(s, d))


@query("nb_id:l", W("SELECT min(nb_id) AS nb_id FROM fps GROUP BY fp", "fps"))
def dedup_corpus(s, d):
    return cmw.notebook_fingerprints(seg.doc_lines(s, d)).groupBy("fp").agg(F.min("nb_id").alias("nb_id"))


@query("nb_id:l pos:l h:s", W("SELECT nb_id, pos, h FROM (SELECT *, row_number() OVER (PARTITION BY h ORDER BY nb_id, pos) AS k FROM ne) WHERE k = 1", "ne"))
def dedup_snippets(s, d):
    first = lines(s, d).groupBy("h").agg(F.min(F.struct("nb_id", "pos")).alias("f"))
    return first.select("h", "f.nb_id", "f.pos")


@query("nb_id:l template:l", W("""SELECT c.nb_id, t.nb_id AS template FROM counts c JOIN counts t ON c.h = t.h AND c.nb_id > t.nb_id JOIN tpl ON tpl.nb_id = t.nb_id JOIN (SELECT nb_id, sum(n) AS own FROM counts GROUP BY 1) o ON o.nb_id = c.nb_id
GROUP BY c.nb_id, t.nb_id, o.own HAVING sum(c.n) >= 0.8 * o.own""", "counts", "fps", tpl="SELECT min(nb_id) AS nb_id FROM fps GROUP BY fp HAVING count(*) >= 2"))
def dedup_templates(s, d):
    c = cmw.counts(lines(s, d))
    t = cmw.notebook_clones(cmw.notebook_fingerprints(seg.doc_lines(s, d))).select(F.col("first_nb").alias("template"))
    return R.deviated(c, t, 0.8)


@query("h:s size:l n_repo:l median_loc:l", W("SELECT * FROM groups WHERE size >= 2 AND median_loc >= 2 AND n_repo >= 3 ORDER BY n_repo DESC, size DESC, h LIMIT 20", "groups"))
def function_candidates(s, d):
    return cmw.groups(lines(s, d)).where("size >= 2 AND median_loc >= 2 AND n_repo >= 3").orderBy(F.desc("n_repo"), F.desc("size"), "h").limit(20)


@query("cells:l clones:l groups:l uniques:l ratio:d mean_freq:d median_freq:d mean_edge:d", W("SELECT (SELECT count(*) FROM cells) AS cells, t.*, (SELECT avg(freq) FROM freq) AS mean_freq, (SELECT quantile_cont(freq, 0.5) FROM freq) AS median_freq, (SELECT avg(edge) FROM conn) AS mean_edge FROM (" + _TOTALS + ") t", "groups", "freq", "conn"))
def clone_report(s, d):
    return R.headline(seg.notebooks(s, d), seg.doc_lines(s, d))


@query("repo:s cells:l clones:l ratio:d", W("SELECT repo, count(*) AS cells, count_if(is_clone) AS clones, avg(CASE WHEN is_clone THEN 1.0 ELSE 0.0 END) AS ratio FROM flags GROUP BY repo", "flags"))
def clones_by_repository(s, d):
    return cmw.flags(lines(s, d)).groupBy("repo").agg(F.count("*").alias("cells"), F.count_if("is_clone").alias("clones"), F.avg(F.col("is_clone").cast("double")).alias("ratio"))


@query("lang:s cells:l clones:l running:l", W("SELECT lang, cells, clones, sum(clones) OVER (ORDER BY lang) AS running FROM (SELECT lang, count(*) AS cells, count_if(is_clone) AS clones FROM flags GROUP BY lang)", "flags"))
def clones_by_language(s, d):
    g = cmw.flags(lines(s, d)).groupBy("lang").agg(F.count("*").alias("cells"), F.count_if("is_clone").alias("clones"))
    return g.withColumn("running", F.sum("clones").over(Window.orderBy("lang")))
