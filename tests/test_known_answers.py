"""Hand-sized frames with known answers, distribution tails against tabulated values, invariants and plan assertions."""

import math
from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from snippetclones.functions import normalize as N
from snippetclones.functions import tails
from snippetclones.operators import cmw, connections, corpus, frequency, language, nearmiss, stats
from snippetclones.plans import explain
from snippetclones.streaming import events

CELL = "nb_id long, repo string, lang string, pos int, code string, loc int"


def cells(spark, rows):
    return spark.createDataFrame([(n, r, "en", p, c, 1) for n, r, p, c in rows], CELL)


@pytest.fixture(scope="module")
def small(spark):
    c = cells(spark, [(1, "r1", 0, "x"), (1, "r1", 1, "x "), (1, "r1", 2, "y"), (2, "r1", 0, " x"), (3, "r2", 0, "x"), (3, "r2", 1, "z")])
    return c.select("nb_id", "repo", F.lit("en").alias("lang")).distinct(), cmw.non_empty(c)


def test_connections_known(small):
    nbs, ne = small
    n = cmw.counts(ne)
    conn = connections.inter_mean(connections.per_notebook(nbs, n), connections.partners(n))
    got = {r.nb_id: (r.edge, r.c0, r.sc, r.m, r.ic) for r in conn.collect()}
    assert got == {1: (5, 3, 2, 1, 2.0), 2: (3, 2, 1, 1, 1.0), 3: (3, 0, 3, 1, 3.0)}
    ends = {r.nb_id: r.edge for r in connections.per_notebook(nbs, n, "endpoint").collect()}
    assert ends == {1: 6, 2: 3, 3: 3}


def test_frequency_known(small):
    nbs, ne = small
    for strategy in ("agg_join", "window"):
        got = {r.nb_id: r.freq for r in frequency.per_notebook(nbs, cmw.flags(ne, strategy)).collect()}
        assert got == {1: pytest.approx(2 / 3), 2: 1.0, 3: 0.5}


def test_cloned_notebooks(spark):
    c = cells(spark, [(1, "r", 0, "a"), (1, "r", 1, "b"), (2, "r", 0, "a"), (2, "r", 1, " b "), (3, "r", 0, "b"), (3, "r", 1, "a"), (4, "r", 0, "a")])
    got = cmw.notebook_clones(cmw.notebook_fingerprints(c)).collect()
    assert [(r.size, r.first_nb) for r in got] == [(2, 1)]


@pytest.mark.parametrize("a,b,linked", [("a b c d e", "a b c d f", True), ("a b c d e", "a b c d e f", True), ("a b c d", "a b c d e", True), ("a b c d e", "a b c x y", False)])
def test_near_miss_pairs(spark, a, b, linked):
    bags = nearmiss.distinct_bags(nearmiss.tokenised(cells(spark, [(1, "r", 0, a), (2, "r", 0, b)])))
    assert nearmiss.pairs(bags).count() == int(linked) == nearmiss.brute_force(bags).count()


def test_not_transitive(spark):
    words = [f"t{i}" for i in range(1, 15)]
    bags = nearmiss.distinct_bags(nearmiss.tokenised(cells(spark, [(1, "r", 0, " ".join(words[:10])), (2, "r", 0, " ".join(words[2:12])), (3, "r", 0, " ".join(words[4:]))])))
    assert nearmiss.open_triples(nearmiss.pairs(bags)).first()[0] == 1


def test_white_space_and_comments(spark):
    c = cells(spark, [(1, "r", 0, "a b"), (2, "r", 0, "a\tb"), (3, "r", 0, "a b # note"), (4, "r", 0, " \t\n")])
    assert cmw.totals(cmw.non_empty(c)).first()[:3] == (2, 1, 1)
    assert nearmiss.distinct_bags(nearmiss.tokenised(c)).count() == 1


def test_components_of_a_long_chain(spark):
    names = [f"b{i:03d}" for i in range(101)]
    found = spark.createDataFrame([*zip(names, names[1:], strict=False), ("x", "y")], "a string, b string")
    assert {r.bag_id: r.root for r in nearmiss.components(found).collect()} == dict.fromkeys(names, "b000") | {"x": "x", "y": "x"}
    assert nearmiss.components(found.where("false")).count() == 0


def test_first_user_over_several_pieces(spark, tmp_path):
    """A group that comes in pieces, later rows first: the first user is the one of the least instant and id."""
    rows = [(i, datetime(2024, 1, 1) + timedelta(minutes=(200 - i) // 2), 1000 + i, "click", 0.0, "p") for i in range(200)]
    e = spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string")
    e.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    key, before = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set(key, "10")
    try:
        assert [(r.first_user, r.size) for r in events.first_seen(spark, str(tmp_path)).collect()] == [(1199, 200)]
    finally:
        spark.conf.set(key, before)


def test_ranks_and_signed_rank(spark):
    h = stats.histogram(spark.createDataFrame([(10,), (20,), (20,), (30,)], "x int"), "x")
    for distributed in (False, True):
        assert {r.v: r.rank for r in stats.mid_ranks(h, distributed=distributed).collect()} == {10: 1.0, 20: 2.5, 30: 4.0}
    r = stats.signed_rank(spark.createDataFrame([(0, 1), (2, 0), (3, 0), (1, 1)], "a int, b int"), "a", "b").first()
    assert (r.n, r.v) == (3, 5.0)


def test_adjustments(spark):
    t = spark.createDataFrame([(0.01,), (0.02,), (0.03,), (0.04,)], "p double")
    assert [round(r.adjusted, 10) for r in stats.adjust(t).collect()] == [0.04] * 4
    assert sorted(round(r.adjusted, 10) for r in stats.adjust(t, "bonferroni").collect()) == [0.04, 0.08, 0.12, 0.16]


@pytest.mark.parametrize("x", [0.5, 12.732684, 31.870802, 50.0, 70.0, 127.3, 400.0])
def test_chi2_tail_of_three_degrees_in_closed_form(x):
    want = math.erfc(math.sqrt(x / 2)) + math.sqrt(2 * x / math.pi) * math.exp(-x / 2)
    assert tails.log_p("chi2", x, 3) == pytest.approx(math.log(want), rel=1e-12)


@pytest.mark.parametrize("kind,x,a,b,p", [("normal", 1.959964, 0, 0, 0.05), ("chi2", 7.814728, 3, 0, 0.05), ("t", 2.228139, 10, 0, 0.05), ("f", 3.708265, 3, 10, 0.05)])
def test_tails(kind, x, a, b, p):
    assert tails.p_value(kind, x, a, b) == pytest.approx(p, rel=1e-5)


def test_tail_far_out():
    assert tails.log_p("normal", 40.0) / math.log(10) == pytest.approx(-349.1, abs=0.6)


def test_languages(spark):
    t = spark.createDataFrame([("pythonX",), ("PYTHON",), ("r",), ("rust",), (None,), ("Julia",), ("scala-2",)], "l string")
    assert [r[0] for r in t.select(language.to_group(F.col("l"))).collect()] == ["PYTHON", "OTHER", "R", "OTHER", "UNDEFINED", "JULIA", "SCALA"]


def test_urls(spark):
    t = spark.createDataFrame([("HTTP://www.Host.org:80/A/#x",), ("https://host.org/A",)], "u string")
    assert len({r[0] for r in t.select(corpus.canonical_url(F.col("u"))).collect()}) == 1


def test_sanitise_is_idempotent(spark):
    lines = spark.createDataFrame([("1,2,3,4",), ("1,2,3,4",), ("x1,2,3,5",), ("1,2,3",), ("1,2,3,4,5",)], "value string")
    once, report = nearmiss.sanitise(lines)
    assert once.count() == 2 and report.first().malformed == 2
    again, _ = nearmiss.sanitise(once.select(F.concat_ws(",", "p1", "f1", "p2", "f2").alias("value")))
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, once.collect()))


def test_accounting(spark):
    from snippetclones.sources import segment as seg

    d = "/root/testdata/sf0.001"
    c = seg.doc_lines(spark, d)
    t = cmw.totals(cmw.non_empty(c)).first()
    empty = c.where(N.strip_ws(F.col("code")) == "").count()
    assert t.clones + t.uniques + empty == c.count()


def test_plans(spark):
    from snippetclones.sources import segment as seg

    d = "/root/testdata/sf0.001"
    explain.check(cmw.flags(cmw.non_empty(seg.doc_lines(spark, d))))
    explain.check(connections.per_notebook(seg.notebooks(spark, d), cmw.counts(cmw.non_empty(seg.doc_lines(spark, d)))))
    explain.check(nearmiss.pairs(nearmiss.distinct_bags(nearmiss.tokenised(seg.doc_lines(spark, d)))))
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in explain.text(seg.doc_lines(spark, d).where("lang = 'en'"))


def test_sessions_stay_out_of_the_driver(spark, tmp_path):
    """Sessions are read back from files; a sink in memory would put each into the driver."""
    at = lambda m: datetime(2024, 1, 1) + timedelta(minutes=m)
    spark.createDataFrame([(1, 7, "a", "p", at(0)), (2, 7, "a", "p", at(20)), (3, 7, "a", "p", at(50)), (4, 8, "a", "p", at(5))], "event_id long, user_id long, event_type string, props string, ts timestamp").write.parquet(f"{tmp_path}/events.parquet")
    out = events.sessions(spark, str(tmp_path))
    assert sorted((r.user_id, r.n) for r in out.collect()) == [(7, 1), (7, 2), (8, 1)]
    assert out.inputFiles()
