"""Oracle SQL building blocks: common table expressions by name, put together in order of need."""

from __future__ import annotations

LINE_CELLS = """cells AS (SELECT nb_id, repo, lang, pos, code, greatest(1, len(regexp_extract_all(code, '[.!?]+'))) AS loc FROM (
  SELECT doc_id AS nb_id, source AS repo, lang, unnest(range(0, len(s))) AS pos, unnest(s) AS code FROM (SELECT *, string_split(text, chr(10)) AS s FROM documents)))"""
BLOCK_CELLS = """cells AS (SELECT nb_id, repo, lang, pos, code, len(string_split(code, chr(10))) AS loc FROM (
  SELECT nb_id, repo, lang, p // 3 AS pos, string_agg(l, chr(10) ORDER BY p) AS code FROM (
    SELECT doc_id AS nb_id, source AS repo, lang, unnest(range(0, len(s))) AS p, unnest(s) AS l FROM (SELECT *, string_split(text, chr(10)) AS s FROM documents)) GROUP BY nb_id, repo, lang, p // 3))"""
WHOLE_CELLS = "cells AS (SELECT doc_id AS nb_id, source AS repo, lang, 0 AS pos, text AS code, len(string_split(text, chr(10))) AS loc FROM documents)"
TURN_CELLS = "cells AS (SELECT conv_id AS nb_id, 'r' || (conv_id % 10) AS repo, 'chat' AS lang, turn AS pos, text AS code, len(string_split(text, chr(10))) AS loc FROM conversations)"
HOST = r"regexp_replace(regexp_extract(lower(url), '^[a-z]+://([^/?#:]+)', 1), '^(www|m)\.', '')"
PAGE_CELLS = rf"""cells AS (SELECT nb_id, repo, lang, pos, code, 1 AS loc FROM (
  SELECT page_id AS nb_id, {HOST} AS repo, regexp_extract(html, '<html[^>]*lang="([a-z]+)', 1) AS lang, unnest(range(0, len(b))) AS pos, unnest(b) AS code
  FROM (SELECT *, regexp_extract_all(html, '<(?:p|li|h1)[^>]*>([^<]*)<', 1) AS b FROM pages)))"""
ORDER_CELLS = """cells AS (SELECT l_orderkey AS nb_id, CAST(o_custkey AS VARCHAR) AS repo, c_mktsegment AS lang, l_linenumber AS pos, l_partkey || '#' || CAST(l_quantity AS BIGINT) AS code, 1 AS loc
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)"""

PAGE_NBS = rf"""nbs AS (SELECT page_id AS nb_id, {HOST} AS repo, regexp_extract(html, '<html[^>]*lang="([a-z]+)', 1) AS lang FROM pages)"""
ORDER_NBS = "nbs AS (SELECT o_orderkey AS nb_id, CAST(o_custkey AS VARCHAR) AS repo, c_mktsegment AS lang FROM orders JOIN customer ON o_custkey = c_custkey)"
SESSION_CELLS = """cells AS (SELECT user_id * 1000000 + s AS nb_id, CAST(user_id AS VARCHAR) AS repo, event_type AS lang, row_number() OVER (PARTITION BY user_id, s ORDER BY ts, event_id) - 1 AS pos, concat_ws('#', event_type, props) AS code, 1 AS loc FROM (
  SELECT *, sum(CASE WHEN coalesce(epoch_us(ts) - before > 1800000000, true) THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
    SELECT *, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events)))"""
BENCH_CELLS = """cells AS (SELECT nb_id, repo, lang, pos, code, greatest(1, len(regexp_extract_all(code, '[.!?]+'))) AS loc FROM (
  SELECT -item_id - 1 AS nb_id, 'benchmark' AS repo, 'en' AS lang, unnest(range(0, len(s))) AS pos, unnest(s) AS code FROM (SELECT *, string_split(text, chr(10)) AS s FROM benchmark)))"""
TEMPLATED_CELLS = f"cells AS (WITH {LINE_CELLS.replace('cells AS', 'dl AS', 1)}, {BENCH_CELLS.replace('cells AS', 'bl AS', 1)} SELECT * FROM dl UNION ALL SELECT * FROM bl)"


def _integral(upper: str, integrand: str) -> str:
    """Simpson's rule over 0 to ``upper``; ``{u}`` stands for the variable."""
    u = f"(i * ({upper}) / 2000.0)"
    return f"(({upper}) / 6000.0 * list_sum(list_transform(range(0, 2001), lambda i: (CASE WHEN i = 0 OR i = 2000 THEN 1 WHEN i % 2 = 1 THEN 4 ELSE 2 END) * {integrand.replace('{u}', u)})))"


def p_normal(z: str) -> str:
    """Two-sided tail of the normal distribution."""
    return f"greatest(0.0, 1 - sqrt(2 / pi()) * {_integral(f'abs({z})', 'exp(-0.5 * {u} * {u})')})"


def p_chi2(x: str, df: str) -> str:
    """Upper tail of the chi-square distribution, integrated over the root."""
    return f"greatest(0.0, 1 - 2 / (2 ** ({df} / 2.0) * gamma({df} / 2.0)) * {_integral(f'sqrt({x})', f'{{u}} ** ({df} - 1) * exp(-0.5 * {{u}} * {{u}})')})"


def p_t(t: str, df: str) -> str:
    """Two-sided tail of Student's distribution."""
    return f"greatest(0.0, 1 - 2 * exp(lgamma(({df} + 1) / 2.0) - lgamma({df} / 2.0)) / sqrt({df} * pi()) * {_integral(f'abs({t})', f'(1 + {{u}} * {{u}} / ({df})) ** (-(({df}) + 1) / 2.0)')})"


CTE = {
    "cells": LINE_CELLS,
    "nbs": "nbs AS (SELECT doc_id AS nb_id, source AS repo, lang FROM documents)",
    "hc": r"hc AS (SELECT *, md5(n) AS h FROM (SELECT *, regexp_replace(code, '[ \t\n\r\f\x0B]+', '', 'g') AS n FROM cells))",
    "ne": "ne AS (SELECT * FROM hc WHERE n <> '')",
    "groups": "groups AS (SELECT h, count(*) AS size, count(DISTINCT nb_id) AS n_nb, count(DISTINCT repo) AS n_repo, floor(quantile_cont(loc, 0.5)) AS median_loc, min(code) AS sample FROM ne GROUP BY h)",
    "flags": "flags AS (SELECT ne.*, g.size, g.size >= 2 AS is_clone, g.median_loc FROM ne JOIN groups g USING (h))",
    "freq": "freq AS (SELECT nb_id, repo, lang, coalesce(cells, 0) AS cells, coalesce(cloned, 0) AS cloned, coalesce(cloned / cells, 0.0) AS freq FROM nbs LEFT JOIN (SELECT nb_id, count(*) AS cells, count_if(is_clone) AS cloned FROM flags GROUP BY nb_id) USING (nb_id))",
    "counts": "counts AS (SELECT nb_id, repo, h, count(*) AS n FROM ne GROUP BY ALL)",
    "edges": "edges AS (SELECT a.nb_id AS x, b.nb_id AS y, a.repo AS rx, b.repo AS ry FROM ne a JOIN ne b ON a.h = b.h AND (a.nb_id, a.pos) < (b.nb_id, b.pos))",
    "ends": "ends AS (SELECT x AS nb_id, ry AS other, rx AS repo FROM edges UNION ALL SELECT y, rx, ry FROM edges WHERE x <> y)",
    "conn": """conn AS (SELECT n.nb_id, n.repo, coalesce(c.cells, 0) AS cells, coalesce(e.edge, 0) AS edge, coalesce(e.edge / c.cells, 0.0) AS norm, coalesce(e.c0, 0) AS c0, coalesce(e.sc, 0) AS sc, coalesce(e.m, 0) AS m, coalesce(e.sc / nullif(e.m, 0), 0.0) AS ic
  FROM nbs n LEFT JOIN (SELECT nb_id, count(*) AS cells FROM ne GROUP BY nb_id) c USING (nb_id)
  LEFT JOIN (SELECT nb_id, count(*) AS edge, count_if(repo = other) AS c0, count_if(repo <> other) AS sc, count(DISTINCT CASE WHEN repo <> other THEN other END) AS m FROM ends GROUP BY nb_id) e USING (nb_id))""",
    "fps": "fps AS (SELECT nb_id, md5(string_agg(h, ',' ORDER BY pos, h)) AS fp, count(*) AS n_cells FROM hc GROUP BY nb_id)",
}
_NEEDS = {"hc": ["cells"], "ne": ["hc"], "groups": ["ne"], "flags": ["groups"], "freq": ["flags", "nbs"], "counts": ["ne"], "edges": ["ne"], "ends": ["edges"], "conn": ["ends", "nbs"], "fps": ["hc"]}

# Near-miss blocks: one language, comments out, bags of two tokens or more.
CTE |= {
    "sl": r"""sl AS (SELECT nb_id, repo, pos, code, regexp_replace(regexp_replace(code, '(?s)"{3}.*?"{3}', '', 'g'), '#[^\n]*', '', 'g') AS stripped FROM cells WHERE lang = 'en')""",
    "tk": r"""tk AS (SELECT *, len(toks) AS n_tok, md5(array_to_string(toks, ' ')) AS bag_id FROM (
  SELECT nb_id, repo, pos, code, len(list_filter(string_split(stripped, chr(10)), lambda x: trim(regexp_replace(x, '[\t\r\f\x0B]', ' ', 'g')) <> '')) AS sloc,
         list_sort(list_filter(regexp_split_to_array(stripped, '[^\p{L}\p{N}_]+'), lambda t: t <> '')) AS toks FROM sl))""",
    "tok": "tok AS (SELECT * FROM tk WHERE sloc > 0 AND n_tok >= 2)",
    "bags": "bags AS (SELECT bag_id, any_value(n_tok) AS n_tok, any_value(toks) AS toks, count(*) AS mult FROM tok GROUP BY bag_id)",
    "bt": "bt AS (SELECT bag_id, n_tok, t, count(*) AS c FROM (SELECT bag_id, n_tok, unnest(toks) AS t FROM bags) GROUP BY ALL)",
    "ov": "ov AS (SELECT x.bag_id AS a, y.bag_id AS b, greatest(x.n_tok, y.n_tok) AS m, sum(least(x.c, y.c)) AS overlap FROM bt x JOIN bt y ON x.t = y.t AND x.bag_id < y.bag_id AND 10 * least(x.n_tok, y.n_tok) >= 7 * greatest(x.n_tok, y.n_tok) GROUP BY 1, 2, 3)",
    "prs": "prs AS (SELECT a, b, overlap, overlap / m AS sim FROM ov WHERE 10 * overlap >= 8 * m)",
    "nmf": "nmf AS (SELECT tok.*, (b.mult > 1 OR l.bag_id IS NOT NULL) AS is_clone FROM tok JOIN bags b USING (bag_id) LEFT JOIN (SELECT DISTINCT unnest([a, b]) AS bag_id FROM prs) l USING (bag_id))",
    "nbe": "nbe AS (SELECT doc_id AS nb_id, source AS repo, lang FROM documents WHERE lang = 'en')",
    "nfreq": "nfreq AS (SELECT nb_id, repo, coalesce(cells, 0) AS cells, coalesce(cloned, 0) AS cloned, coalesce(cloned / cells, 0.0) AS freq FROM nbe LEFT JOIN (SELECT nb_id, count(*) AS cells, count_if(is_clone) AS cloned FROM nmf GROUP BY nb_id) USING (nb_id))",
    "adj": "adj AS (SELECT a, b FROM prs UNION ALL SELECT b, a FROM prs UNION ALL SELECT bag_id, bag_id FROM bags)",
    "nedge": "nedge AS (SELECT x.nb_id AS x, y.nb_id AS y, x.repo AS rx, y.repo AS ry FROM tok x JOIN adj ON x.bag_id = adj.a JOIN tok y ON y.bag_id = adj.b AND (x.nb_id, x.pos) < (y.nb_id, y.pos))",
    "nends": "nends AS (SELECT x AS nb_id, rx AS repo, ry AS other FROM nedge UNION ALL SELECT y, ry, rx FROM nedge WHERE x <> y)",
    "nconn": """nconn AS (SELECT n.nb_id, n.repo, coalesce(c.cells, 0) AS cells, coalesce(e.edge, 0) AS edge, coalesce(e.edge / c.cells, 0.0) AS norm, coalesce(e.c0, 0) AS c0, coalesce(e.sc, 0) AS sc, coalesce(e.m, 0) AS m, coalesce(e.sc / nullif(e.m, 0), 0.0) AS ic
  FROM nbe n LEFT JOIN (SELECT nb_id, count(*) AS cells FROM tok GROUP BY nb_id) c USING (nb_id)
  LEFT JOIN (SELECT nb_id, count(*) AS edge, count_if(repo = other) AS c0, count_if(repo <> other) AS sc, count(DISTINCT CASE WHEN repo <> other THEN other END) AS m FROM nends GROUP BY nb_id) e USING (nb_id))""",
}
_NEEDS |= {"sl": ["cells"], "tk": ["sl"], "tok": ["tk"], "bags": ["tok"], "bt": ["bags"], "ov": ["bt"], "prs": ["ov"], "nmf": ["prs", "bags"], "nfreq": ["nmf", "nbe"], "adj": ["prs", "bags"], "nedge": ["adj", "tok"], "nends": ["nedge"], "nconn": ["nends", "nbe", "tok"]}


def with_(body: str, *names: str, cells: str = LINE_CELLS, nbs: str | None = None, **extra: str) -> str:
    """``WITH`` the named blocks, what they need first, then ``extra`` blocks in order, then the body."""
    order: list[str] = []

    def need(n: str) -> None:
        for m in _NEEDS.get(n, []):
            need(m)
        if n not in order:
            order.append(n)

    for n in names:
        need(n)
    parts = [cells if n == "cells" else nbs if n == "nbs" and nbs else CTE[n] for n in order] + [f"{k} AS ({v})" for k, v in extra.items()]
    return f"WITH {', '.join(parts)}\n{body}" if parts else body


def summary(col: str, source: str, label: str | None = None) -> str:
    q = ", ".join(f"quantile_cont({col}, {p}) AS {n}" for p, n in ((0.1, "p10"), (0.25, "p25"), (0.5, "median"), (0.75, "p75"), (0.9, "p90")))
    return f"SELECT '{label or col}' AS measure, min({col}) AS min, {q}, avg({col}) AS mean, max({col}) AS max FROM {source}"


SUMMARY_SPEC = "measure:s min:d p10:d p25:d median:d mean:d p75:d p90:d max:d"


def spearman_sql(source: str, x: str, y: str) -> str:
    rank = lambda c: f"(rank() OVER (ORDER BY {c}) + (count(*) OVER (PARTITION BY {c}) - 1) / 2)"
    return f"SELECT count(*) AS n, corr(rx, ry) AS rho, corr(rx, ry) * sqrt((count(*) - 2) / (1 - corr(rx, ry) ** 2)) AS statistic FROM (SELECT {rank(x)} AS rx, {rank(y)} AS ry FROM {source})"


def signed_sql(source: str, x: str, y: str) -> str:
    d = f"(SELECT round(abs({x} - {y}), 9) AS a, {x} - {y} AS d FROM {source} WHERE {x} <> {y})"
    return f"""SELECT n, v, (v - n * (n + 1) / 4 - sign(v - n * (n + 1) / 4) * 0.5) / nullif(sqrt(n * (n + 1) * (2 * n + 1) / 24 - ties / 48), 0) AS statistic FROM (
  SELECT count(*)::DOUBLE AS n, sum(CASE WHEN d > 0 THEN r END) AS v, (SELECT sum(c::DOUBLE ** 3 - c) FROM (SELECT a, count(*) AS c FROM {d} GROUP BY a)) AS ties
  FROM (SELECT d, rank() OVER (ORDER BY a) + (count(*) OVER (PARTITION BY a) - 1) / 2 AS r FROM {d}))"""
