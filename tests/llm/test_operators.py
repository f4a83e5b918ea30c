"""The training-data operators against brute force, the public libraries, round trips and held-out accuracy, with their edge cases."""

import hashlib
import struct

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from snippetclones.llm import ann_tree, bpe_codec, exact_topk, language_id, line_dedup, mixing, pii, quality, queries, simhash, token_counts, vectors

DIR = "/root/testdata/sf0.001"
ODD = ["", " ", "\n\n a", "Σας ΟΔΟΣ", "a<|endoftext|>b <|startoftext|>", "it's we'RE 'll''s 're 'r", "\x1c\x1d a\x85b c", "日本語🙂", "aaaa" * 900, "12³½", "a'", "''r", "É é"]
DOC = "doc_id long, text string, lang string, source string, n_chars long, rid string, ids_le string, keep string"


def docs(spark, texts, source="s"):
    """Rows with clashing extra columns, a null id and a repeated row."""
    return spark.createDataFrame([(None if i == 1 else i, t, "en", source, 0, "x", "y", "z") for i, t in enumerate(texts)], DOC)


@pytest.fixture(scope="module")
def texts():
    return [r[0] for r in duckdb.execute(f"SELECT text FROM '{DIR}/documents.parquet'").fetchall()]


def test_bpe_equals_library(texts):
    from tokenizers import Tokenizer

    path = queries.tokenizer_path("word_bpe_49k.json")
    own, ref = bpe_codec.BpeCodec(path), Tokenizer.from_file(path)
    for t in [*texts[:60], *ODD]:
        want = ref.encode(t, add_special_tokens=False).ids
        assert own.encode(t) == want
        assert own.decode(want) == ref.decode(want, skip_special_tokens=False)


def test_bpe_tests_no_token_once_a_prefix_has_its_last_one(texts, monkeypatch):
    """Fewer pairs are tested than tokens end in the words, and memo and patterns give the same ids in whatever order."""
    path = queries.tokenizer_path("word_bpe_49k.json")
    monkeypatch.setattr(bpe_codec, "MEMO_WORDS", 50)
    own = bpe_codec.BpeCodec(path)
    calls, compatible = [], own.model.compatible
    monkeypatch.setattr(own.model, "compatible", lambda a, b: calls.append((a, b)) or compatible(a, b))
    monkeypatch.setattr(own.model, "tested", lambda key: None, raising=False)
    words = list(dict.fromkeys(w for t in texts[:20] for w in own.words(t or "")))[:400]
    ends = sum(k <= end for w in words for end, (k, _) in own.matcher.iter(own.model.spell(w)))
    ids = [own.word_ids(w) for w in words]
    assert 0 < len(calls) < ends
    assert [list(struct.unpack(f"<{len(x) // 4}I", x)) for x in (own.memo[w][0] for w in [*words, *words[::-1]])] == ids + ids[::-1]
    assert len(own.memo) <= 50 >= len(own.memo.old)


def test_bpe_frame(spark):
    out = bpe_codec.encode_documents(docs(spark, ["The cat", None, "", "The cat"]), queries.tokenizer_path("word_bpe_49k.json"))
    got = out.select("ids_le", "decoded", bpe_codec.ids_array().alias("ids")).collect()
    assert got[0][:2] == got[3][:2] and got[1].decoded == "" == got[2].decoded
    assert list(struct.unpack(f"<{len(got[0].ids_le) // 4}I", got[0].ids_le)) == got[0].ids


def test_counts_equal_library(texts):
    from tokenizers import Tokenizer

    path = queries.tokenizer_path("byte_bpe_50k.json")
    own, ref = token_counts.CountTransducer(path), Tokenizer.from_file(path)
    for t in [*texts[:40], *ODD]:
        want = len(ref.encode(t, add_special_tokens=False).ids)
        assert own.count(t) == want
        for chunk in (1, 3, 50):
            assert own.count(t[:400], chunk) == len(ref.encode(t[:400], add_special_tokens=False).ids)


def test_counts_frame(spark):
    out = token_counts.count_tokens(docs(spark, ["é", None, "", "a b " * 600]), queries.tokenizer_path("byte_bpe_50k.json")).collect()
    assert [(r.n_bytes, r.over_limit) for r in out] == [(2, False), (0, False), (0, False), (2400, True)]


def brute_lines(rows, words):
    """Every line in a run of enough words that starts at an earlier place too, by trying all runs."""
    seqs = {k: [(i, x) for i, x in enumerate(t.split("\n")) if x.split()] for k, t in rows}
    gone = {k: set() for k in seqs}
    runs = {}
    for k in sorted(seqs):
        s = seqs[k]
        for a in range(len(s)):
            for b in range(a + 1, len(s) + 1):
                run = tuple(x for _, x in s[a:b])
                if sum(len(x.split()) for x in run) >= words:
                    if runs.setdefault(run, (k, a)) != (k, a):
                        gone[k].update(i for i, _ in s[a:b])
    return {k: "\n".join(x for i, x in enumerate(t.split("\n")) if i not in gone[k]) for k, t in rows}


def test_line_dedup_brute_force(spark):
    rng = np.random.default_rng(5)
    lines = ["a", "b", "a b", "c d e", "one two three four", "", "x"]
    rows = [(i, "\n".join(rng.choice(lines, rng.integers(1, 9)))) for i in range(40)]
    for words in (1, 3, 4, 7):
        got = {r.doc_id: r.text for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), words).collect()}
        assert got == brute_lines(rows, words)


def test_line_dedup_edges(spark):
    d = docs(spark, ["one two three four\nleft", "one two three four", None, "", "\n\n"])
    got = line_dedup.dedup_lines(d).collect()
    assert {(r.doc_id, r.text) for r in got} == {(0, "one two three four\nleft"), (None, ""), (2, None), (3, ""), (4, "\n\n")}
    assert line_dedup.dedup_lines(d.where("false")).count() == 0


def vec(spark, rows):
    return vectors.usable(spark.createDataFrame(rows, "vec_id long, embedding array<float>, v string"))


def test_exact_topk(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(900, 8)).astype(np.float32)
    x[100:400] = x[7]
    rows = vec(spark, [(i, v.tolist(), "x") for i, v in enumerate(x)] + [(900, None, "x"), (901, [None] * 8, "x"), (902, [float("nan")] * 8, "x"), (903, [], "x"), (None, [1.0] * 8, "x")])
    z = rows
    out = exact_topk.exact_topk(z, vectors.query_rows(z, 50), 5, tile_rows=128, tile_queries=8).collect()
    q = np.floor(256 * x.astype(float)).astype(int)
    for i in range(0, 900, 50):
        s = q @ q[i]
        want = [(j, s[j]) for j in np.lexsort((np.arange(900), -s)) if j != i][:5]
        assert [(r.vec_id, r.score) for r in sorted((r for r in out if r.query_id == i), key=lambda r: r.rank)] == want
    assert exact_topk.exact_topk(z.where("vec_id = 50"), vectors.query_rows(z, 50).where("vec_id = 50")).count() == 0
    assert exact_topk.exact_topk(z.where("false"), z.where("false")).count() == 0


def test_ann_recall(spark):
    e = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = vectors.usable(e).where(F.exists("v", lambda v: v != 0))
    out = ann_tree.nearest_neighbours(rows, vectors.query_rows(rows, 20), 20).collect()
    p = rows.toPandas().sort_values("vec_id")
    ids, x = p.vec_id.to_numpy(), np.stack(p.v.to_numpy())
    hit = 0
    for i in ids[ids % 20 == 0]:
        s = x @ x[np.searchsorted(ids, i)]
        best = set([int(j) for j in ids[np.lexsort((ids, -s))] if j != i][:20])
        hit += len(best & {r.vec_id for r in out if r.query_id == i})
    assert hit / (20 * (ids % 20 == 0).sum()) >= 0.9
    assert ann_tree.nearest_neighbours(rows.where("false"), rows.where("false")).count() == 0
    same = vec(spark, [(i, [1.0, 0.5], "x") for i in range(60)])
    got = sorted((r.rank, r.vec_id) for r in ann_tree.nearest_neighbours(same, vectors.query_rows(same, 20), 5).collect() if r.query_id == 20)
    assert got == [(1, 0), (2, 1), (3, 2), (4, 3), (5, 4)]


def test_language_held_out(spark):
    out = queries.op4_language_id(spark, "/root/testdata/sf0.01").where("held_out").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id")
    assert out.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0] > 0.95


def test_language_edges(spark):
    d = docs(spark, [None, "", "123 !!", "the cat"])
    assert [r.lang_pred for r in language_id.predict(d, {}).collect()] == ["und"] * 4
    assert language_id.fit(d.where("false")) == {}
    held = language_id.fit(d)
    assert [r.lang_pred for r in language_id.predict(d, held).collect()] == ["und", "und", "und", "en"]


def test_simhash_brute_force(spark):
    rng = np.random.default_rng(1)
    texts = [" ".join(f"w{x}" for x in rng.integers(0, 400, 60)) for _ in range(30)]
    texts += [t.replace("w1 ", "q ") for t in texts[:10]] + texts[:5] + [None, "", "  ", "one", "ONE"]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")

    def fp(t):
        w = (t or "").encode().lower().split()
        h = [xxhash.xxh64_intdigest(b" ".join(s), 42) for s in (zip(w, w[1:], w[2:]) if len(w) >= 3 else [w] if w else [])]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    f = [fp(t) for t in texts]
    root = list(range(len(f)))
    for _ in f:
        for i in range(len(f)):
            root[i] = min(root[j] for j in range(len(f)) if (f[i] ^ f[j]).bit_count() <= 3)
    got = {r.doc_id: (r.fp & (1 << 64) - 1, r.component_id) for r in simhash.near_duplicates(d)[0].collect()}
    assert got == {i: (f[i], root[i]) for i in range(len(f))}


def test_near_pairs_all_radii(spark):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 62, 8)
    fps = sorted({int(b) ^ sum(1 << int(k) for k in rng.choice(62, rng.integers(0, 8), replace=False)) for b in base for _ in range(12)})
    nodes = spark.createDataFrame(list(enumerate(fps)), "node long, fp long")
    for radius, segments in ((3, 2), (5, 3), (7, 4)):
        want = {(i, j) for i in range(len(fps)) for j in range(i + 1, len(fps)) if (fps[i] ^ fps[j]).bit_count() <= radius}
        got = [tuple(r) for r in simhash.near_pairs(nodes, radius, segments).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_verified_near_duplicates(spark):
    words = [f"word{i}" for i in range(120)]
    near = [*words[:60], "changed", *words[61:]]
    far = [x if i % 9 else "other" for i, x in enumerate(words)]
    d = docs(spark, [" ".join(words), " ".join(near), " ".join(far), " ".join(words), None, ""])
    kept = simhash.drop_near_duplicates(d, radius=7, segments=4, features="distinct", verify=(5, 0.8))
    assert kept.columns == d.columns and sorted(r.doc_id for r in kept.collect()) == [0, 2, 4]
    assert simhash.drop_near_duplicates(d.where("false"), radius=7, segments=4, features="distinct", verify=(5, 0.8)).count() == 0


def test_verified_near_duplicates_exact(spark):
    """Appended and short copies included, links are those of an exact join, also where fingerprints are far apart."""
    rng = np.random.default_rng(5)
    prose = lambda n: [f"v{int(x)}" for x in rng.zipf(1.3, n) % 3000]
    base = [prose(int(n)) for n in rng.integers(8, 400, 60)]
    texts = [*base, *[w + prose(max(1, round(len(w) * share))) for share in (0.05, 0.1, 0.15, 0.2) for w in base], [], ["a"], ["a", "a"], *base[:3]]
    sets = [set(zip(*(w[i:] for i in range(5)), strict=False)) if len(w) >= 5 else {tuple(w)} for w in texts]
    root, far = list(range(len(texts))), 0
    prints = [simhash.fingerprint(simhash.hashes([x.encode() for x in dict.fromkeys(w)])) & (1 << 64) - 1 for w in texts]
    for i, x in enumerate(sets):
        for j in range(i):
            if 10 * len(x & sets[j]) >= 8 * len(x | sets[j]):
                root = [min(root[i], root[j]) if r in (root[i], root[j]) else r for r in root]
                far += (prints[i] ^ prints[j]).bit_count() > 7
    assert far > 20
    d = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)], "doc_id long, text string")
    got = simhash.near_duplicates(d, radius=7, segments=4, features="distinct", verify=(5, 0.8))[0]
    assert {r.doc_id: r.component_id for r in got.collect()} == dict(enumerate(root))


def test_links_within_the_radius_come_from_fingerprints_alone(spark, monkeypatch):
    """Without what fingerprints find exactly the links beyond the radius are left, without the prefix join exactly those within it."""
    rng = np.random.default_rng(6)
    base = [[f"v{int(x)}" for x in rng.integers(0, 3000, int(n))] for n in rng.integers(20, 200, 25)]
    texts = [*base, *[w + [f"u{i}_{j}" for j in range(max(1, round(len(w) * share)))] for i, w in enumerate(base) for share in (0.04, 0.12)]]
    sets = [set(zip(*(w[i:] for i in range(5)), strict=False)) for w in texts]
    prints = [simhash.fingerprint(simhash.hashes([x.encode() for x in dict.fromkeys(w)])) & (1 << 64) - 1 for w in texts]
    near, far = (list(range(len(texts))) for _ in range(2))
    for i, x in enumerate(sets):
        for j in range(i):
            if 10 * len(x & sets[j]) >= 8 * len(x | sets[j]):
                root = near if (prints[i] ^ prints[j]).bit_count() <= 7 else far
                low, high = sorted((root[i], root[j]))
                root[:] = [low if r == high else r for r in root]
    assert all(sum(r != i for i, r in enumerate(root)) > 5 for root in (near, far))
    d = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)], "doc_id long, text string")

    def roots_without(*names):
        with monkeypatch.context() as m:
            for name in names:
                full = getattr(simhash, name, None)
                m.setattr(simhash, name, lambda *a, full=full, **k: full(*a, **k).where("false"), raising=False)
            got = simhash.near_duplicates(d, radius=7, segments=4, features="distinct", verify=(5, 0.8))[0]
            return [r.component_id for r in got.orderBy("doc_id").collect()]

    assert roots_without("_near") == far
    assert roots_without("prefix_leaders", "prefix_pairs") == near


def test_mixing_targets_and_fit(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 100), ("c", 1000), (None, 0)], "source string, source_size long")
    got = {r.source: r.target for r in mixing.targets(sizes).collect()}
    want = {"a": 20.0, "b": 200.0, "c": 1.5 * 1110 - 220, None: 0.0}
    assert {k: pytest.approx(v) for k, v in want.items()} == got
    rng = np.random.default_rng(4)
    for _ in range(1500):
        lengths = sorted({int(x) for x in rng.integers(1, rng.choice([8, 60, 300]), rng.integers(1, 7))})
        counts = [int(x) for x in rng.integers(1, 5, len(lengths))]
        budget = int(rng.integers(0, sum(a * c for a, c in zip(lengths, counts, strict=True)) + 4))
        take = mixing.fit_counts(lengths, counts, budget)
        reach = {0}
        for a, c in zip(lengths, counts, strict=True):
            reach = {r + a * k for r in reach for k in range(c + 1)}
        total = sum(a * t for a, t in zip(lengths, take, strict=True))
        assert all(0 <= t <= c for t, c in zip(take, counts, strict=True)) and total <= budget
        assert total == max(r for r in reach if r <= budget)


def test_mixing_query(spark):
    for _ in range(2):
        rows = queries.op8_source_mix(spark, DIR).collect()
        by = {}
        for r in rows:
            assert r.taken in (0, r.size, 2 * r.size)
            by.setdefault((r.source_size, r.target), []).append(r.taken)
        for (size, target), taken in by.items():
            assert target <= 2 * size + 1e-6 and abs(sum(taken) - target) <= max(2, 0.02 * target)
    again = {r.doc_id: r.taken for r in queries.op8_source_mix(spark, DIR).collect()}
    assert again == {r.doc_id: r.taken for r in rows}


def test_mixing_edges(spark):
    d = docs(spark, [None, "", "a b c", "a b c", "d"], source=None)
    got = mixing.mix(d)[0].collect()
    assert len(got) == 5 and all(r.copies == 0 for r in got if r.size == 0)
    assert mixing.mixed_documents(d.where("false")).count() == 0


def test_quality_held_out(spark):
    d = "/root/testdata/sf0.1"
    rows = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text")
    grades = quality.graded(spark.read.parquet(f"{d}/labels.parquet")).cache()
    half = F.crc32(F.col("doc_id").cast("string")) % 2 == 0
    out = quality.rate(rows, quality.fit(rows, grades.where(half))).join(grades.where(~half), "doc_id")
    kept = {r.grade: r.k for r in out.groupBy("grade").agg(F.avg(F.col("keep").cast("double")).alias("k")).collect()}
    assert kept[2] > 0.98 and kept[1] < 0.1 and kept[0] < 0.1


def test_quality_edges(spark):
    d = docs(spark, [None, "", "word"])
    assert quality.fit(d, spark.createDataFrame([], "doc_id long, grade int")) is None
    got = quality.rate(d, None)
    assert [r.keep for r in got.collect()] == [True] * 3 and got.columns.count("keep") == 1
    m = quality.fit_rows([(*quality.features("good text here"), 2), (*quality.features("bad ### ###"), 0)] * 20)
    assert np.all(np.diff(m.thresholds) > 0) if len(m.thresholds) > 1 else True
    assert quality.rate(d, m).count() == 3


def test_pii_brute_force(texts):
    import re

    def base(t):
        out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
        for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
            n = re.sub("[^0-9]", "", m[0])
            if 13 <= len(n) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(n[::-1])) % 10 == 0:
                out.append(("card", *m.span()))
        return out + [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15]

    odd = ["a@b.c@d.e", "@x.y", "a@@b.c", "x@y", "1.2.3.4.5.6.7.8", "999.1.1.1", "4111 1111-1111 1111", "4111 1111 1111 1112", "+1 (212) 555-0100 x", "++44 20 7946 0958", "a.b+c@d-e.f.g. z"]
    for t in [*texts, *odd]:
        assert [(s["kind"], s["start"], s["end"]) for s in pii.find(t) if s["kind"] in pii.KINDS[:4]] == base(t)


def test_pii_added_kinds():
    assert [s["kind"] for s in pii.find("IBAN GB82 WEST 1234 5698 7654 32 please")] == ["iban"]
    assert not [s for s in pii.find("IBAN GB82 WEST 1234 5698 7654 33 please") if s["kind"] == "iban"]
    assert [s["kind"] for s in pii.find("social security 123-45-6789")] == ["national_id"] and not pii.find("part 123-45-6789")
    assert pii.find(None) == [] == pii.find("")
    assert pii.redact("to a@b.cd now", pii.find("to a@b.cd now")) == "to <email> now"


def test_pii_query_digest(spark):
    for r in queries.op10_personal_data(spark, "/root/testdata/sf0.01").collect():
        base = [x for x in r.spans.split(",") if x.split(":")[0] in pii.KINDS[:4]]
        assert r.base_sha256 == hashlib.sha256(",".join(base).encode()).hexdigest()
        assert r.n_email + r.n_ip + r.n_card + r.n_phone == len(base)


def test_pipeline(spark):
    import corpus_pipeline

    source = spark.read.parquet(f"{DIR}/documents.parquet")
    now = source
    for name, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, DIR)
        assert now.columns == source.columns, name
        now = corpus_pipeline.written(now, name)
    out = corpus_pipeline.STAGES[-1][1](spark, now, DIR)
    assert out.count() == now.count() > 0
    assert all(r.n_tokens * 4 == len(r.ids_le) for r in out.collect())


def test_sketch_bound_keeps_every_similar_pair(spark):
    rng = np.random.default_rng(11)
    rows, sets = [], []
    for size in (0, 1, 5, 40, 300, 4000):
        whole = rng.integers(-(1 << 62), 1 << 62, size)
        for lost in (0.0, 0.05, 0.1, 0.11, 0.12, 0.2, 0.5):
            new = whole.copy()
            new[: int(size * lost)] = rng.integers(-(1 << 62), 1 << 62, int(size * lost))
            sets.append(np.unique(new))
            rows.append((len(rows), 0, len(sets[-1]), *(int(x) for x in simhash.parity_sketch(sets[-1]))))
    nodes = spark.createDataFrame(rows, "node long, fp long, m long, " + ", ".join(f"{c} long" for c in simhash.SKETCH_WORDS))
    got = {tuple(r) for r in simhash.near_pairs(nodes, 3, 2, similarity=0.8).collect()}
    share = lambda x, y: len(np.intersect1d(x, y)) / max(1, len(np.union1d(x, y))) if len(x) or len(y) else 1.0
    pairs = {(i, j): share(sets[i], sets[j]) for i in range(len(sets)) for j in range(i + 1, len(sets))}
    assert {p for p, s in pairs.items() if s >= 0.8} <= got
    assert not {p for p in got if pairs[p] < 0.5 and len(sets[p[1]]) <= 300}  # sketches of far larger sets are full and exclude nothing


def _planes(rng, n):
    """A text of ``n`` code points from all planes, rich in blanks and contractions."""
    out = []
    while len(out) < n:
        c = int(rng.integers(0, 0x110000)) if rng.random() < 0.5 else int(rng.integers(32, 0x250))
        out.append(str(rng.choice(list(" '\n\tsretvlldm"))) if rng.random() < 0.3 else "" if 0xD800 <= c < 0xE000 else chr(c))
    return "".join(out)


def test_codec_and_counts_on_all_planes():
    from tokenizers import Tokenizer

    from snippetclones.llm.char_classes import library_classes

    rng = np.random.default_rng(8)
    one, six = queries.tokenizer_path("word_bpe_49k.json"), queries.tokenizer_path("byte_bpe_50k.json")
    codec, ref1, counter, ref6 = bpe_codec.BpeCodec(one), Tokenizer.from_file(one), token_counts.CountTransducer(six), Tokenizer.from_file(six)
    edge = [t for a, b in library_classes().unlike for c in (a, b) for t in (chr(c) + "'re a", "a" + chr(c), "1" + chr(c) + " " + chr(c))]
    for t in [*edge, *(_planes(rng, int(rng.integers(1, 40))) for _ in range(1200))]:
        want = ref1.encode(t, add_special_tokens=False).ids
        assert codec.encode(t) == want and codec.decode(want) == ref1.decode(want, skip_special_tokens=False)
        assert {counter.count(t, c) for c in (1, 2, 5, token_counts.CHUNK)} == {len(ref6.encode(t, add_special_tokens=False).ids)}


def test_counts_of_endless_classes(monkeypatch):
    """Millions of characters of one class, and fewer compiled states than the text would need."""
    import time

    from tokenizers import Tokenizer

    path = queries.tokenizer_path("byte_bpe_50k.json")
    own, ref = token_counts.CountTransducer(path), Tokenizer.from_file(path)
    for t in ("a" * 10**6, " " * 10**6, "'" * 10**6, "日本" * 300_000, "\n \t" * 200_000):
        began = time.time()
        assert own.count(t) == len(ref.encode(t, add_special_tokens=False).ids)
        assert time.time() - began < 30
    monkeypatch.setattr(token_counts, "STATES", 500)
    rng = np.random.default_rng(1)
    t = "".join(rng.choice(list("abcdefghijklmnop 0123"), 100_000))
    assert own.count(t, 1000) == len(ref.encode(t, add_special_tokens=False).ids)
    assert len(own.merge.states) < 500 + 2 * token_counts.SLICE


def test_exact_topk_large_components(spark):
    """No clip: whole numbers of any length where a double can't hold the scores, and the nearest long beyond."""
    big = spark.createDataFrame([(0, [300000.0, 0.5]), (1, [400000.0, -0.5]), (2, [-1e30, 1.0]), (3, [1e30, 2.0]), (50, [1.0, 1.0])], "vec_id long, embedding array<double>")
    rows = vectors.usable(big)
    got = {(r.query_id, r.vec_id): r.score for r in exact_topk.exact_topk(rows, rows).collect()}
    assert got[0, 1] == 300000 * 256 * 400000 * 256 - 128 * 128
    assert got[0, 2] == -(1 << 63) and got[0, 3] == (1 << 63) - 1
    assert got[50, 0] == 256 * 300000 * 256 + 256 * 128


def test_exact_topk_skips_postings():
    rng = np.random.default_rng(4)
    x = np.floor(256 * rng.normal(size=(4000, 32)) * np.repeat([[1.0], [0.1]], [40, 3960], axis=0))
    index = exact_topk.ImpactIndex(x)
    found = index.search(x[:32], 5, [np.array([i]) for i in range(32)])
    s = x[:32] @ x.T
    s[np.arange(32), np.arange(32)] = -np.inf
    assert all((f[0] == np.lexsort((np.arange(4000), -s[i]))[:5]).all() for i, f in enumerate(found))
    assert index.read < 0.7 * 32 * len(index.rows)


CLASH = "`doc_id` long, `Text` string, lang string, source string, n_chars long, `a.b` string, `__text` string, text_ string, rid string, _rid string, gone_ string, lines_ string, full_ string, copies string, n_tokens string, n_lines string, expected_grade string, lang_pred string, pii string"
LONG = "word " * 300_000


def test_every_operator_takes_odd_tables(spark):
    """Dots, capitals and the operators' own names among the columns; null, empty and very long texts, repeated rows, a null id; an empty table."""
    texts = ["one two three four\nfive six seven eight", None, "", "one two three four\nfive six seven eight", LONG, "call +1 212 555 0100"]
    odd = spark.createDataFrame([(None if i == 1 else 5 if i == 3 else i, t, "en", None if i == 2 else "s", 0, *["x"] * 14) for i, t in enumerate(texts)], CLASH)
    one, six = queries.tokenizer_path("word_bpe_49k.json"), queries.tokenizer_path("byte_bpe_50k.json")
    model = quality.fit_rows([(*quality.features("good text here"), 2), (*quality.features("bad ### ###"), 0)] * 20)
    runs = {
        "codec": lambda d: bpe_codec.encode_documents(d, one),
        "lines": line_dedup.dedup_lines,
        "language": lambda d: language_id.predict(d, language_id.fit(d)),
        "counts": lambda d: token_counts.count_tokens(d, six),
        "simhash": lambda d: simhash.near_duplicates(d)[0],
        "simhash rows": lambda d: simhash.drop_near_duplicates(d, radius=7, segments=4, features="distinct", verify=(5, 0.8)),
        "mix": lambda d: mixing.mix(d)[0],
        "mixed": mixing.mixed_documents,
        "quality": lambda d: quality.rate(d, model),
        "pii": pii.find_personal_data,
    }
    for name, run in runs.items():
        rows = run(odd).collect()
        assert len(rows) == 6 if name not in ("simhash rows", "mixed") else rows, name
        if "a.b" in rows[0].asDict():
            assert rows[0]["a.b"] == "x" and rows[0]["gone_"] == "x", name
        assert run(odd.where("false")).count() == 0, name
    cleaned = {r["Text"] for r in line_dedup.dedup_lines(odd).collect()}
    assert "" in cleaned and LONG in cleaned and None in cleaned


def test_numbers_hold_for_shuffled_input(spark):
    """Rows dealt anew at every evaluation: what is deleted and taken still belongs to its row."""
    d = spark.createDataFrame([(i, f"shared line of five words\nown words of document {i} here") for i in range(200)], "doc_id long, text string")
    out = line_dedup.dedup_lines(d.orderBy(F.rand())).collect()
    assert all(r.text.endswith(f"own words of document {r.doc_id} here") for r in out) and sum(r.n_removed for r in out) == 199
    s = d.withColumn("source", F.lit("s")).orderBy(F.rand())
    taken = mixing.mixed_documents(s).groupBy("doc_id", "text").count().collect()
    assert all(r.text.endswith(f"document {r.doc_id} here") and r["count"] <= 2 for r in taken)


def test_language_brute_force(texts):
    """The smallest total over pieces, compressed one by one with a fresh compressor for each dictionary."""
    import zstandard

    held = {"a": "\n".join(t for t in texts[:20] if t).encode(), "b": "\n".join(t for t in texts[20:40] if t).encode()}
    own = language_id.Classifier(held)
    for t in [x for x in texts[40:70] if x and any(c.isalpha() for c in x)]:
        raw = t.encode()
        size = {n: sum(len(zstandard.ZstdCompressor(level=language_id.LEVEL, dict_data=zstandard.ZstdCompressionDict(d, dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_content_size=False, write_checksum=False).compress(raw[i : i + language_id.PIECE])) for i in range(0, len(raw), language_id.PIECE)) for n, d in held.items()}
        best, other = sorted(size, key=lambda n: (size[n], n))
        got = own.predict(t)
        assert got[0] == best and abs(got[1] - (size[other] - size[best]) / size[other]) < 1e-12


def test_languages_of_long_texts_and_many_languages(spark):
    rows = [(i, " ".join(f"tok{i}x{j}" for j in range(40)), f"l{i:03d}", "s") for i in range(300)] + [(900, "zebra quagga okapi " * 900, "long", "s")]
    held = language_id.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string"))
    assert len(held) == 301 and language_id.Classifier(held).predict("quagga zebra okapi zebra quagga okapi")[0] == "long"


def test_quality_brute_force():
    """Fitted weights against a dense evaluation: gradients vanish numerically and no step in any direction lowers the loss."""
    rng = np.random.default_rng(2)
    rows = []
    for i in range(300):
        g = i % 3
        rows.append((*quality.features(" ".join(rng.choice([f"g{g}w{k}" for k in range(4)] + [f"c{k}" for k in range(20)], 30))), g))
    m = quality.fit_rows(rows, steps=1500)
    x = np.zeros((len(rows), len(m.places)))
    for i, (at, value, _) in enumerate(rows):
        j = np.searchsorted(m.places, at)
        ok = (j < len(m.places)) & (m.places[np.minimum(j, len(m.places) - 1)] == at)
        x[i, j[ok]] = value[ok]
    y = np.array([r[2] for r in rows])

    def loss(w, t):
        cum = np.concatenate([np.zeros((len(y), 1)), 1 / (1 + np.exp(-(t[None, :] - (x @ w)[:, None]))), np.ones((len(y), 1))], axis=1)
        return -np.log(np.maximum(cum[np.arange(len(y)), y + 1] - cum[np.arange(len(y)), y], 1e-12)).mean() + 0.5e-6 * (w @ w)

    base = loss(m.weights, m.thresholds)
    assert base < 0.05
    for _ in range(50):
        d = rng.normal(size=len(m.weights))
        assert loss(m.weights + 0.05 * d / np.linalg.norm(d), m.thresholds) > base - 5e-3
    assert np.allclose([m.of(*r[:2]) for r in rows], x @ m.weights)


def test_pipeline_stages_against_brute_force(spark):
    """Each stage on its predecessor's real output, recomputed in plain Python."""
    import corpus_pipeline as p

    documents = spark.read.parquet(f"{DIR}/documents.parquet")
    key = lambda df: sorted(((r.doc_id, r.text, r.source) for r in df.collect()), key=repr)
    model = quality.fit(documents, quality.graded(spark.read.parquet(f"{DIR}/labels.parquet")))
    rated = p.written(p.quality_stage(spark, documents, DIR), "t")
    tail = lambda t: model.tails(np.array([model.score(t)]))[0, -1]
    assert key(rated) == key(documents) if model is None else {r[0] for r in key(rated)} == {r[0] for r in key(documents) if tail(r[1]) >= quality.REJECT_BELOW}
    lines = p.written(p.line_stage(spark, rated, DIR), "t")
    left = brute_lines([(k, t or "") for k, t, _ in key(rated)], line_dedup.MIN_WORDS)
    assert {r[0]: r[1] or "" for r in key(lines)} == left
    assert all(r.n_chars == len(r.text or "") for r in lines.collect())
    unique = p.written(p.near_duplicate_stage(spark, lines, DIR), "t")
    sets, ids = {}, [r[0] for r in key(lines)]
    for k, t, _ in key(lines):
        w = (t or "").lower().split()
        sets[k] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    root = {k: k for k in ids}

    def top(k):
        while root[k] != k:
            k = root[k]
        return k

    for i, a in enumerate(ids):
        for b in ids[:i]:
            if 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                root[max(x, y)] = min(x, y)
    assert {r[0] for r in key(unique)} == {k for k in ids if root[k] == k}
    mixed = p.written(p.mixing_stage(spark, unique, DIR), "t")
    size = lambda t: len((t or "").split())
    sources = {}
    for _, t, s in key(unique):
        sources.setdefault(s, []).append(size(t))
    goal = {r.source: r.target for r in mixing.targets(spark.createDataFrame([(s, sum(v)) for s, v in sources.items()], "source string, source_size long")).collect()}
    for s, v in sources.items():
        got = sum(size(t) for _, t, x in key(mixed) if x == s)
        whole, rest = divmod(round(goal[s]), sum(v))
        reach = 1
        for n in v:
            reach |= reach << n
        assert got == whole * sum(v) + (reach & ((1 << (rest + 1)) - 1)).bit_length() - 1, s
    assert max(mixed.groupBy("doc_id").count().toPandas()["count"]) <= 2
    from tokenizers import Tokenizer

    ref = Tokenizer.from_file(queries.tokenizer_path("word_bpe_49k.json"))
    texts_of = {k: t for k, t, _ in key(mixed)}
    for r in p.encoding_stage(spark, mixed, DIR).collect():
        assert list(struct.unpack(f"<{r.n_tokens}I", r.ids_le)) == ref.encode(texts_of[r.doc_id] or "", add_special_tokens=False).ids


def test_ann_visits_until_k_rows(spark):
    """One visit would end in a leaf of few rows; the walk goes on until k others are there."""
    rng = np.random.default_rng(6)
    x = np.concatenate([rng.normal(size=(600, 4)) + 20 * np.eye(4)[i % 4] for i in range(2)] + [np.full((3, 4), -50.0)])
    rows = vec(spark, [(i, v.tolist(), "x") for i, v in enumerate(x)])
    tree = ann_tree.KMeansTree(x.astype(float), 4)
    sizes = dict(zip(*(a.tolist() for a in np.unique(tree.route(x), return_counts=True)), strict=True))
    assert all(sum(sizes.get(leaf, 0) for leaf in tree.visit(x[i], 1, None, sizes, 21)) >= 21 for i in (0, 700, 1201))
    out = ann_tree.nearest_neighbours(rows, vectors.query_rows(rows, 20), 20).groupBy("query_id").count().collect()
    assert all(r["count"] == 20 for r in out) and len(out) == -(-len(x) // 20)
