"""Operators on links and ranks against plain Python on small random inputs."""

import itertools
import time
from collections import Counter
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from snippetclones import session
from snippetclones.operators import connections, distributions, nearmiss, stats
from snippetclones.plans import corpus_queries


def test_components_of_a_long_chain(spark):
    """200 bags, each near only to its neighbours: one root, in whatever order the links come."""
    rng = np.random.default_rng(3)
    names = [f"b{i:03d}" for i in rng.permutation(200)]
    links = [(min(a, b), max(a, b)) for a, b in itertools.pairwise(names)]
    got = nearmiss.components(spark.createDataFrame(links, "a string, b string")).collect()
    assert len(got) == 200 and {r.root for r in got} == {"b000"}


def test_open_triples(spark):
    rng = np.random.default_rng(4)
    links = {(int(a), int(b)) for a, b in rng.integers(0, 30, (140, 2)) if a < b}
    near = {(a, b) for a, b in links} | {(b, a) for a, b in links}
    want = sum((x, z) not in near for y in range(30) for x, z in itertools.combinations([v for v in range(30) if (y, v) in near], 2))
    assert nearmiss.open_triples(spark.createDataFrame(sorted(links), "a long, b long")).first()[0] == want
    assert nearmiss.open_triples(spark.createDataFrame([], "a long, b long")).first()[0] == 0


@pytest.mark.parametrize("listed", [0, 2, 64])
def test_partners_by_lists_and_bitmaps(spark, monkeypatch, listed):
    monkeypatch.setattr(connections, "LISTED", listed)
    rng = np.random.default_rng(listed)
    rows = sorted({(int(n), f"r{int(n) % 11}", f"h{int(h)}") for n, h in zip(rng.integers(0, 40, 160), rng.zipf(1.6, 160) % 25, strict=True)})
    counts = spark.createDataFrame([(*r, 1) for r in rows], "nb_id long, repo string, h string, n long")
    want = {n: len({r for m, r, h in rows if (n, f"r{n % 11}", h) in rows and r != f"r{n % 11}"}) for n, _, _ in rows}
    assert {r.nb_id: r.m for r in connections.partners(counts).collect()} == want


def test_ranks_in_one_task_and_by_ranges(spark):
    hist = spark.createDataFrame([(int(v), int(c)) for v, c in enumerate(np.random.default_rng(1).integers(1, 9, 500))], "v long, c long")
    one, many = (sorted((r.v, r.rank, r.upto) for r in stats.mid_ranks(hist, distributed=d).collect()) for d in (False, True))
    assert one == many == sorted((r.v, r.rank, r.upto) for r in stats.mid_ranks(hist).collect())


def test_top_value_leaves_only_where_it_stands_alone(spark):
    bins = lambda xs: {r.bin: r.cnt for r in distributions.hist(spark.createDataFrame([(x,) for x in xs], "v long"), "v", drop_top=1).collect()}
    assert bins([1, 2, 9]) == {1: 1, 2: 1} and bins([1, 9, 9]) == {1: 1, 9: 2} and bins([]) == {}


def test_pairs_equal_brute_force_with_places(spark):
    rng = np.random.default_rng(9)
    rows = []
    for i in range(120):
        base = rng.integers(0, 12, 10)
        if i >= 60:
            base = np.array([int(x[1:]) for x in rows[i - 60][2]])
            base[rng.integers(0, len(base))] = 99
        rows.append((f"b{i:03d}", 10, sorted(f"t{x}" for x in base), 1))
    bags = spark.createDataFrame(rows, "bag_id string, n_tok int, toks array<string>, mult long").dropDuplicates(["toks"])
    for tenths in (7, 8, 9):
        got = {(r.a, r.b, r.overlap) for r in nearmiss.pairs(bags, tenths).collect()}
        assert got == {(r.a, r.b, r.overlap) for r in nearmiss.brute_force(bags, tenths).collect()} and got


def test_no_shared_folder_on_a_cluster():
    class Conf:
        def get(self, *_):
            return None

    class Context:
        master = "spark://somewhere:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(RuntimeError):
        session.shared_dir(Session())


def test_pairwise_tests_of_many_groups(spark):
    rng = np.random.default_rng(2)
    d = spark.createDataFrame([(f"g{int(g)}", float(v)) for g, v in zip(rng.integers(0, 7, 300), rng.integers(0, 20, 300), strict=True)], "g string, y double")
    out = stats.pairwise_ranksum(d, "g", "y").collect()
    assert len(out) == 21 and all(0 <= r.p <= 1 for r in out)
    assert stats.adjust(stats.pairwise_ranksum(d, "g", "y")).where(F.col("adjusted") < F.col("p")).count() == 0


@pytest.mark.parametrize("tenths", [7, 8])
def test_unlike_bags_end_inside_their_group(spark, tenths):
    """Bags of all sketch sizes that share a rare token are no candidates unless they are near; no near pair is lost."""
    rng = np.random.default_rng(tenths)
    rows = []
    for i, n in enumerate([40, 150, 260, 520, 1100] * 8):
        base = [f"rare{i % 4}", *(f"w{int(x)}" for x in rng.integers(0, 4000, n))]
        rows += [base, base[: -n // 8] + [f"new{i}"] * 2] if i % 5 == i // 8 else [base]
    bags = spark.createDataFrame([(f"bag {i}", len(x), sorted(x), 1) for i, x in enumerate(rows)], "bag_id string, n_tok int, toks array<string>, mult long")
    want = {(r.a, r.b, r.overlap) for r in nearmiss.brute_force(bags, tenths).collect()}
    assert {(r.a, r.b, r.overlap) for r in nearmiss.pairs(bags, tenths).collect()} == want and want
    assert nearmiss.candidates(nearmiss.stored(bags), tenths).count() <= len(want) + 20
    assert nearmiss.pairs(bags.where("false"), tenths).count() == 0

@pytest.mark.parametrize("tenths", [5, 8])
def test_bands_propose_the_pairs_of_their_join(spark, tenths):
    """What a block says of its pairs is what the join on bands would find."""
    rng = np.random.default_rng(tenths + 20)
    rows = []
    for i in range(150):
        base = [f"w{int(x)}" for x in rng.integers(0, 5000, 20)]
        rows += [base, base[: 2 * tenths] + [f"new{i}"] * (20 - 2 * tenths)]
    bags = spark.createDataFrame([(f"bag {i}", len(x), sorted(x), 1) for i, x in enumerate(rows)], "bag_id string, n_tok int, toks array<string>, mult long")
    known = nearmiss.stored(bags)
    found = nearmiss.numbered_pairs(known, tenths, banded=True).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "proposed").collect()
    joined = {(r.a, r.b) for r in nearmiss.lsh_candidates(known).collect()}
    assert len(found) >= 150 and any(r.proposed for r in found) and (tenths == 8 or not all(r.proposed for r in found))
    assert all(r.proposed == ((r.a, r.b) in joined) for r in found)
    assert nearmiss.numbered_pairs(known.where("false"), tenths, banded=True).count() == 0


def test_near_miss_leaves_no_shuffle_files_and_no_tokens(spark, tmp_path):
    """Bags and pairs take their own folders only: shuffles go when a cut is written, tokens when the bags are."""
    rows = [(i, "s", "en", f"alpha beta gamma word{i % 9} word{i % 7}\n" * 2) for i in range(60)]
    spark.createDataFrame(rows, "doc_id long, source string, lang string, text string").write.parquet(str(tmp_path / "documents.parquet"))
    left = lambda kind: {p for p in Path(session.shared_dir(spark).removeprefix("file:")).glob(f"{kind}_*")}
    disk = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    files = lambda: {f.split("_")[1] for f in (disk.getAllFiles().apply(i).getName() for i in range(disk.getAllFiles().size())) if f.startswith("shuffle_")}
    tokens, before = left("tokens"), files()
    cells, bags, _ = corpus_queries.near(spark, str(tmp_path))
    for _ in range(50):  # they are removed in the background
        if len(files() - before) <= 3:
            break
        time.sleep(0.1)
    assert len(files() - before) <= 3  # item counts and two sums are collected, not written
    assert left("tokens") == tokens and "toks" not in cells.columns
    assert cells.count() == 120 and bags.agg(F.sum("mult")).first()[0] == 120


@pytest.mark.parametrize("links", ["clique", "mixed"])
def test_triangles_by_colours(spark, links):
    """Every triangle is counted once, whatever colours its ends have, and wedges don't leave their group."""
    rng = np.random.default_rng(4)
    pairs = {(a, b) for a, b in itertools.combinations(range(40), 2) if links == "clique" or rng.random() < 0.2}
    want = sum((a, b) in pairs and (b, c) in pairs and (a, c) in pairs for a, b, c in itertools.combinations(range(40), 3))
    for kind, of in (("long", int), ("string", "n{}".format)):
        edges = spark.createDataFrame([(of(a), of(b)) for a, b in sorted(pairs)], f"u {kind}, v {kind}")
        out = nearmiss.triangles(edges)
        assert out.agg(F.sum("n")).first()[0] == want > 0
        assert "SortMergeJoin" not in out._jdf.queryExecution().toString()
    assert nearmiss.triangles(edges.where("false")).count() == 0


def near_misses(rng, n):
    """Bags of which every second one is near its predecessor."""
    rows = []
    for i in range(n):
        base = [f"w{int(x)}" for x in rng.integers(0, 900, 20)]
        rows += [base, [*base[:-2], f"new{i}", f"new{i}"]]
    return rows


def test_rounds_have_every_bag_and_pair_and_hold_a_share_of_the_shuffles(spark, monkeypatch):
    """A large input is worked on in rounds: same bags, same pairs, and the most that is shuffled at once is a share of it."""
    rows = [(i, f"r{i % 3}", "en", i, " ".join(x)) for i, x in enumerate(near_misses(np.random.default_rng(5), 300))]
    cells = spark.createDataFrame([*rows, *rows[:50]], "nb_id int, repo string, lang string, pos int, code string").withColumn("loc", F.lit(1))
    tok = nearmiss.tokenised(cells).drop("code")
    bags = {r.bag_id: r.mult for r in nearmiss.distinct_bags(tok).collect()}
    want = {(r.a, r.b, r.overlap) for r in nearmiss.brute_force(nearmiss.distinct_bags(tok)).collect()}
    left = lambda: {p for kind in ("tokens", "proposed", "blocks", "candidates") for p in Path(session.shared_dir(spark).removeprefix("file:")).glob(f"{kind}_*")}
    earlier, seen, before = left(), [], nearmiss.visits
    monkeypatch.setattr(nearmiss, "visits", lambda *a, **k: seen.append(before(*a, **k)) or seen[-1])
    for size, rounds in ((1 << 20, 1), (64, 4)):
        monkeypatch.setattr(nearmiss, "GROUP", size)
        seen.clear()
        kept, known = nearmiss.collapsed(tok)
        assert {r.bag_id: r.mult for r in known.collect()} == bags and known.select("node").distinct().count() == len(bags) and kept.count() == 650
        pairs = nearmiss.numbered_pairs(known)
        assert {(r.a, r.b, r.overlap) for r in pairs.collect()} == want and len(want) >= 300
        counts = [x.count() for x in seen]
        assert len(counts) == rounds and max(counts) <= 1.6 * sum(counts) / rounds
        for r in pairs.limit(3).collect():
            assert {r.x, r.y} == {x.node for x in known.where(F.col("bag_id").isin(r.a, r.b)).collect()}
    assert left() == earlier


def test_only_bags_of_a_pair_travel(spark):
    known = spark.createDataFrame([(n, f"b{n}") for n in (0, 1, 7, 8, 32767, 32768, 32769, (1 << 33) + 5, (3 << 56) + 12)], "node long, bag_id string")
    for want in ({0, 8, 32768}, {1, 7, 32767, 32769, (3 << 56) + 12}, {(1 << 33) + 5}, set()):
        ends = spark.createDataFrame([(n,) for n in [*want, *want, 40000]], "node long")
        assert {r.node for r in nearmiss.among(known, ends).collect()} == want


def test_links_inside_look_through_the_rarer_bag(spark):
    """Bag 0 is in 200 notebooks, its 40 neighbours in one each: 40 rows are looked up, not 8000."""
    counts = spark.createDataFrame([(i, 0, 1 + i % 2) for i in range(200)] + [(i, 1 + i, 3) for i in range(40)], "nb_id long, bag_id long, n long")
    pairs = spark.createDataFrame([(0, 1 + i) for i in range(40)], "a long, b long")
    got = connections.links_inside(pairs, counts)
    assert sorted((r.nb_id, r.n * r.m) for r in got.collect()) == [(i, 3 * (1 + i % 2)) for i in range(40)]
    assert {r.nb_id for r in nearmiss.self_clones(counts, pairs).collect()} == {i for i in range(200) if i % 2 or i < 40}


def unlike_bags():
    """Bags of like and unlike sizes with repeated tokens by id, and their near pairs at 0.8 by plain counting."""
    rng = np.random.default_rng(11)
    rows = [[f"w{int(x)}" for x in rng.zipf(1.5, int(n)) % 40] for n in rng.integers(1, 60, 50)]
    rows += [[*x[1:], f"new{i}"] for i, x in enumerate(rows[:25])] + [["the"] * 300, ["the"] * 290 + ["of"] * 8, ["only"]]
    ids = {f"b{i:02d}": sorted(x) for i, x in enumerate(rows)}
    want = {}
    for a, b in itertools.combinations(sorted(ids), 2):
        least, most = sum((Counter(ids[a]) & Counter(ids[b])).values()), max(len(ids[a]), len(ids[b]))
        if least and 10 * least >= 8 * most:
            want[a, b] = (least, least / most)
    return ids, want


def test_brute_force_counts_all_pairs_where_bags_meet(spark, monkeypatch):
    """Every pair in several rounds: only bags travel, twice a round, and no table of shared tokens is made."""
    ids, want = unlike_bags()
    bags = spark.createDataFrame([*((i, len(x), x, 1) for i, x in ids.items()), ("none", 0, [], 1)], "bag_id string, n_tok int, toks array<string>, mult long")
    monkeypatch.setattr(nearmiss, "COLOUR", 500)
    left = lambda: set(Path(session.shared_dir(spark).removeprefix("file:")).glob("bags_*"))
    plans, seen, written, meetings, earlier = [], [], nearmiss.C.written, nearmiss.meetings, left()
    monkeypatch.setattr(nearmiss.C, "written", lambda df, *a: plans.append(df._jdf.queryExecution().toString()) or written(df, *a))
    monkeypatch.setattr(nearmiss, "meetings", lambda *a: seen.append(meetings(*a).count()) or meetings(*a))
    out = nearmiss.brute_force(bags)
    assert sorted((r.a, r.b, r.overlap, r.sim) for r in out.collect()) == [(*k, *v) for k, v in sorted(want.items())] and len(want) > 20
    assert len(seen) > 1 and set(seen) == {2 * len(ids)}
    assert not any("Join" in p for p in [*plans, out._jdf.queryExecution().toString()]) and out.schema["overlap"].dataType.typeName() == "integer"
    assert nearmiss.brute_force(bags.where("false")).count() == 0 and left() == earlier


@pytest.mark.parametrize("dense", [1, 5, 1 << 40])
def test_all_overlaps_of_tiles(monkeypatch, dense):
    """Pair by pair, by products of matrices, or both: the same sums, inside a colour and between two."""
    ids, want = unlike_bags()
    for name, value in {"TILE": 7, "CHUNK": 20, "PIECE": 9, "SLICE": 16, "DENSE": dense}.items():
        monkeypatch.setattr(nearmiss, name, value)
    bags = pa.RecordBatch.from_pydict({"bag_id": list(ids), "n_tok": [len(x) for x in ids.values()], "bag": [" ".join(x) for x in ids.values()]})
    runs = pa.Table.from_batches(nearmiss.run_lengths([bags]))
    for colours in ([0] * len(ids), [i % 3 // 2 for i in range(len(ids))]):
        of = dict(zip(ids, colours, strict=True))
        found = nearmiss.all_overlaps(runs.append_column("colour", pa.array(colours, pa.int32())), 8, any(colours)).to_pylist()
        got = sorted((*sorted((r["ida"], r["idb"])), r["overlap"], r["sim"]) for r in found)
        assert got == [(*k, *v) for k, v in sorted(want.items()) if not any(colours) or of[k[0]] != of[k[1]]] and got
    assert nearmiss.all_overlaps(runs.append_column("colour", pa.array([0] * len(ids), pa.int32())), 8, True).num_rows == 0


def test_brute_force_counts_a_pair_once_when_colours_are_empty(spark):
    """Two bags of one colour meet in the group of their colour only, not also where the other colour is missing."""
    rows = [(f"b{i}", 5, ["a", "b", "c", "d", f"x{i}"], 1) for i in range(5)]
    for a, b in itertools.combinations(rows, 2):
        bags = spark.createDataFrame([a, b], "bag_id string, n_tok int, toks array<string>, mult long")
        assert [tuple(r) for r in nearmiss.brute_force(bags).collect()] == [(a[0], b[0], 4, 0.8)]
