"""Operator 7 - SimHash near-duplicates by multi-index hashing.

Fingerprints are cut into segments.  Of two fingerprints within ``radius``
bits, some segment differs in at most ``radius // segments`` bits (0 or 1
here), so a table by segment value is probed with the small Hamming ball
around each segment: the value itself and its one-bit neighbours.  Of a
pair one bit apart exactly one side has that bit at zero, so only zero bits are
flipped.  Matches are verified on all 64 bits, and a pair that an earlier
segment finds is not taken again.

Work is done on classes of equal fingerprints (or equal texts), so a group of
exact copies is one node, and distinct fingerprints bound each node's links.
With ``verify``, links are exactly the pairs whose sets of word shingles have a
Jaccard similarity of the threshold or more, however far apart their
fingerprints are.  Links within ``radius`` bits come from fingerprints alone.
Links beyond come from a prefix join on shingles, rarest first, which leaves out
what lies within ``radius`` and loses nothing else.  Shingles that no other text
holds are counted and never joined; their number, the set's size and a parity
sketch bound a pair's similarity from above inside the joins, so that pairs that
can't reach the threshold never leave them, and those left are compared exactly.
A text without a shared shingle in its prefix has no link and isn't probed.  The
most typical node within ``radius``, and of each shingle, is tried first, and the
full joins skip pairs that are already connected - no link between components is
lost, and a large group of near copies doesn't become all its pairs.

Edge cases: null and empty texts have fingerprint zero and link like others;
rows that repeat a doc_id stay apart; a null doc_id counts as larger than any
other; of equal doc_ids the first row heads its class; an empty table gives no
rows; rows are numbered once, so the input may change its order when evaluated again.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import components, shuffles_freed
from .common import cut, fresh_name, named, numbered, release, written

SEED = 42
BITS = 64
BLOCK, BLOCK_SHINGLES = 1024, 1 << 19  # texts and shingles a side of a verification block, about
BUCKET = 1 << 22  # shingles a bucket, where their holders are counted
FLUSH = 1 << 20  # shingles that a task holds before it deals them out
SLICE = 512  # texts whose shingle sets travel to the JVM together
SKETCH = 512  # bits of a parity sketch, kept as 64-bit words
SKETCH_WORDS = [f"sk{i}" for i in range(SKETCH // BITS)]


def words(text: str | None) -> list[bytes]:
    """Lower-cased (A to Z only) words without ASCII white space."""
    return text.encode("utf-8", "replace").lower().split() if text else []


def shingles(tokens: list[bytes], size: int) -> list[bytes]:
    """Word shingles, repeats included; fewer words give the whole sequence, none gives nothing."""
    if len(tokens) < size:
        return [b" ".join(tokens)] if tokens else []
    return [b" ".join(s) for s in zip(*(tokens[i:] for i in range(size)), strict=False)]


def hashes(features: list[bytes]) -> np.ndarray:
    one = xxhash.xxh64_intdigest
    return np.fromiter((one(f, SEED) for f in features), dtype=np.uint64, count=len(features))


def fingerprint(h: np.ndarray) -> int:
    """A bit is set where more than half of the hashes have it; as a signed 64-bit integer."""
    votes = np.zeros(BITS, np.int64)
    for i in range(0, len(h), 1 << 15):
        votes += np.unpackbits(h[i : i + (1 << 15)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(h)).view(">i8")[0]) if len(h) else 0


def shingle_set(text: str | None, size: int) -> np.ndarray:
    """Ascending distinct hashes of a text's word shingles, as signed 64-bit integers."""
    return np.unique(hashes(shingles(words(text), size)).view(np.int64))


def parity_sketch(distinct: np.ndarray) -> np.ndarray:
    """Bit i is the parity of how many hashes of a set fall on place i; two sketches differ in at most as many bits as the sets have unshared members."""
    odd = np.bincount(distinct & (SKETCH - 1), minlength=SKETCH).astype(np.uint8) & 1
    return np.packbits(odd).view(">i8").astype(np.int64)


def signatures(docs: DataFrame, rid: str, features: str, size: int, doc_id: str = "doc_id", text: str = "text", sketch: int | None = None) -> DataFrame:
    """``(rid, doc_id, fp, th, m, sk)``: fingerprint of the repeated ``shingles`` or of the ``distinct`` words, and a hash of the word sequence.

    With ``sketch``, m and sk are the size and the parity sketch of the set of shingles of so many words, else null.
    """
    source = docs.select(F.col(rid).alias("rid"), named(doc_id).cast("long").alias("doc_id"), named(text).cast("string").alias("t"))

    def run(batches):
        for b in batches:
            fps, ths, sizes, sketches = [], [], [], []
            for t in b["t"]:
                tokens = words(t.as_py())
                parts = shingles(tokens, size) if features == "shingles" else list(dict.fromkeys(tokens))
                fps.append(fingerprint(hashes(parts)))
                ths.append(xxhash.xxh3_128_digest(b" ".join(tokens)))
                held = shingle_set(t.as_py(), sketch) if sketch else None
                sizes.append(None if held is None else len(held))
                sketches.append(None if held is None else parity_sketch(held))
            columns = [b["rid"], b["doc_id"], pa.array(fps, pa.int64()), pa.array(ths, pa.binary()), pa.array(sizes, pa.int64()), pa.array(sketches, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(columns, names=["rid", "doc_id", "fp", "th", "m", "sk"])

    return source.mapInArrow(run, "rid long, doc_id long, fp long, th binary, m long, sk array<long>")


def _segments(count: int) -> list[tuple[int, int]]:
    """(shift, width) of each segment, from the low end."""
    cuts = [BITS * i // count for i in range(count + 1)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def _value(fp, shift: int, width: int):
    return F.shiftrightunsigned(fp, shift).bitwiseAND(F.lit((1 << width) - 1)) if width < BITS else fp


def may_reach(similarity: float, x: str, y: str):
    """Whether sizes and sketches leave room for a Jaccard similarity: never false for a pair that has it.

    Sets of a and b members with d unshared ones have similarity (a + b - d) / (a + b + d), and d is at least the sketches' distance.
    """
    a, b = F.col(f"{x}.m"), F.col(f"{y}.m")
    apart = sum((F.bit_count(F.col(f"{x}.{c}").bitwiseXOR(F.col(f"{y}.{c}"))) for c in SKETCH_WORDS[1:]), F.bit_count(F.col(f"{x}.{SKETCH_WORDS[0]}").bitwiseXOR(F.col(f"{y}.{SKETCH_WORDS[0]}"))))
    return (F.least(a, b) >= F.greatest(a, b) * F.lit(similarity - 1e-9)) & (apart <= (a + b) * F.lit((1 - similarity) / (1 + similarity) + 1e-9))


def _near(nodes: DataFrame, radius: int, segments: int, apart: bool = False, similarity: float | None = None, also: tuple[str, ...] = ()) -> DataFrame:
    """Rows ``x`` and ``y`` of ``nodes`` within ``radius`` bits, each pair once; ``also`` names further columns to keep."""
    ball = radius // segments
    if ball > 1:
        raise ValueError("radius must stay below twice the number of segments")
    parts, fp = _segments(segments), F.col("fp")
    kept = ["node", "fp", *(["root"] if apart else []), *(["m", *SKETCH_WORDS] if similarity else []), *also]
    own = F.array(*[F.struct(F.lit(s).alias("seg"), _value(fp, *p).alias("key")) for s, p in enumerate(parts)])
    table = nodes.select(*kept, F.explode(own).alias("e")).select(*kept, "e.seg", "e.key")
    entry = lambda s, p, bit: F.struct(F.lit(s).alias("seg"), (_value(fp, *p).bitwiseOR(F.lit(1 << bit))).alias("key"), F.lit(True).alias("flipped"))
    probes = F.array(
        *[F.struct(F.lit(s).alias("seg"), _value(fp, *p).alias("key"), F.lit(False).alias("flipped")) for s, p in enumerate(parts)],
        *[F.when(F.shiftrightunsigned(fp, p[0] + bit).bitwiseAND(F.lit(1)) == 0, entry(s, p, bit)) for s, p in enumerate(parts) for bit in (range(p[1]) if ball else ())],
    )
    probe = nodes.select(*kept, F.explode(F.filter(probes, lambda e: e.isNotNull())).alias("e")).select(*kept, "e.seg", "e.key", "e.flipped")
    x, y = probe.alias("x"), table.alias("y")
    diff = F.col("x.fp").bitwiseXOR(F.col("y.fp"))
    earlier = F.lit(False)  # an earlier segment is within its ball, so the pair was found there
    for s in range(segments - 1):
        earlier = earlier | ((F.col("x.seg") > s) & (F.bit_count(_value(diff, *parts[s])) <= ball))
    match = (F.col("x.seg") == F.col("y.seg")) & (F.col("x.key") == F.col("y.key")) & (F.bit_count(diff) <= radius) & (F.col("x.flipped") | (F.col("x.node") < F.col("y.node"))) & ~earlier
    if apart:
        match = match & (F.col("x.root") != F.col("y.root"))
    if similarity:
        match = match & may_reach(similarity, "x", "y")
    return x.join(y, match)


def near_pairs(nodes: DataFrame, radius: int, segments: int, apart: bool = False, similarity: float | None = None) -> DataFrame:
    """Pairs ``(a, b)``, a < b, of ``nodes(node, fp[, root, m, sk0 ..])`` within ``radius`` bits, each once.

    ``apart``: only across roots; ``similarity``: only pairs whose sketches leave room for it.
    """
    return _near(nodes, radius, segments, apart, similarity).select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b"))


def near_leaders(nodes: DataFrame, radius: int, segments: int, similarity: float) -> DataFrame:
    """Pairs of each of ``nodes(node, fp, m, sk0 .., alone)`` with the most typical node (fewest shingles of its own) within ``radius`` bits and with room for ``similarity``."""
    typical = F.col("alone") / F.greatest("m", F.lit(1)) + F.pmod(F.xxhash64("node"), F.lit(1 << 20)) * F.lit(1e-12)  # ties fall alike for all
    both = _near(nodes.withColumn("rank", typical), radius, segments, similarity=similarity, also=("rank",))
    ends = F.array(*[F.struct(F.col(f"{u}.node").alias("u"), F.col(f"{v}.node").alias("v"), F.col(f"{v}.rank").alias("rank")) for u, v in ("xy", "yx")])
    best = both.select(F.explode(ends).alias("e")).groupBy(F.col("e.u").alias("u")).agg(F.min_by("e.v", "e.rank").alias("v"))
    return best.select(F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b")).distinct()


def shared_shingles(docs: DataFrame, size: int, total: int, text: str = "text") -> DataFrame:
    """``(th, item, df)``: shingles that at least two distinct texts hold, for each text (by the hash of its words) that holds them.

    Items are shingle hashes cut to 32 bits and a bucket.  Two of a text that fall together stay two rows and count as
    shared, so a text's missing rows are shingles that nobody else holds.  ``total``, about the number of shingles, sets the buckets.
    """
    buckets = max(32, -(-total // BUCKET))
    source = docs.select(named(text).cast("string").alias("t"))

    def deal(keys, sets):
        """A row for each bucket: holders, how many shingles each has there, and the shingles."""
        flat = np.concatenate(sets).view(np.uint64)
        owner = np.repeat(np.arange(len(keys)), [len(x) for x in sets])
        part = ((flat >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        ends = np.searchsorted(part[order], np.arange(buckets + 1))
        short, names, out = flat.astype(np.uint32), np.array(keys, dtype="V16"), []
        for p in range(buckets):
            at = order[ends[p] : ends[p + 1]]
            if len(at):
                who, counts = np.unique(owner[at], return_counts=True)
                out.append((p, names[who].tobytes(), counts.astype(np.int32).tobytes(), short[at].tobytes()))
        columns = zip(*out, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int32(), pa.binary(), pa.binary(), pa.binary()), strict=True)], names=["p", "keys", "counts", "h"])

    def run(batches):
        keys, sets, held = [], [], 0
        for b in batches:
            for t in b["t"]:
                tokens = words(t.as_py())
                if not tokens:
                    continue
                keys.append(xxhash.xxh3_128_digest(b" ".join(tokens)))
                sets.append(np.unique(hashes(shingles(tokens, size)).view(np.int64)))
                held += len(sets[-1])
                if held >= FLUSH:
                    yield deal(keys, sets)
                    keys, sets, held = [], [], 0
        if keys:
            yield deal(keys, sets)

    def count(key: tuple, rows: pa.Table) -> pa.Table:
        keys = np.frombuffer(b"".join(x.as_py() for x in rows["keys"]), "V16")
        counts = np.frombuffer(b"".join(x.as_py() for x in rows["counts"]), np.int32)
        h = np.frombuffer(b"".join(x.as_py() for x in rows["h"]), np.uint32)
        pairs = keys.view(">u8").reshape(-1, 2)
        order = np.lexsort((pairs[:, 1], pairs[:, 0]))
        ranked = pairs[order]
        fresh = np.ones(len(order), bool)
        fresh[1:] = (ranked[1:] != ranked[:-1]).any(axis=1)
        first = np.zeros(len(keys), bool)
        first[order[fresh]] = True  # equal texts count once
        h, owner = h[np.repeat(first, counts)], np.repeat(np.flatnonzero(first), counts[first])
        order = np.argsort(h, kind="stable")
        h, owner = h[order], owner[order]
        starts = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
        df = np.repeat(runs := np.diff(np.r_[starts, len(h)]), runs)
        keep = df > 1
        item = (np.int64(key[0].as_py()) << np.int64(32)) | h[keep].astype(np.int64)
        names = pa.array([keys[i].tobytes() for i in owner[keep]], pa.binary())
        return pa.table({"th": names, "item": item, "df": df[keep].astype(np.int64)})

    dealt = source.mapInArrow(run, "p int, keys binary, counts binary, h binary")
    return dealt.groupBy("p").applyInArrow(count, "th binary, item long, df long")


def prefixes(nodes: DataFrame, shared: DataFrame, similarity: float) -> DataFrame:
    """``(node, fp, m, sk0 .., alone, item, inner)``: the shingles among which every pair of ``similarity`` or more has one in common.

    All texts order shingles alike, rarest first, so the ``alone`` ones that nobody else holds lead and only shorten the prefix.
    The larger set of a pair needs its first m - ceil(s m) + 1, the other one its first m - ceil(2 s / (1 + s) m) + 1 (``inner``).
    """
    held = shared.groupBy("th").agg(F.array_sort(F.collect_list(F.struct("df", "item"))).alias("held"))
    known = nodes.join(held, "th").withColumn("alone", F.col("m") - F.size("held"))
    reach = lambda share: (F.col("m") - F.ceil(F.col("m") * F.lit(share) - F.lit(1e-9)) + 1 - F.col("alone")).cast("int")
    known = known.withColumn("outer", reach(similarity)).withColumn("nearer", reach(2 * similarity / (1 + similarity))).where("outer > 0")
    first = known.select("node", "fp", "m", *SKETCH_WORDS, "alone", "nearer", F.posexplode(F.slice("held", F.lit(1), F.col("outer"))).alias("at", "e"))
    return first.select("node", "fp", "m", *SKETCH_WORDS, "alone", F.col("e.item").alias("item"), (F.col("at") < F.col("nearer")).alias("inner"))


def may_meet(similarity: float, x: str, y: str):
    """``may_reach``, and the shingles that only one text holds leave room as well: they are unshared in every pair."""
    m = F.col(f"{x}.m") + F.col(f"{y}.m")
    return (F.col(f"{x}.alone") + F.col(f"{y}.alone") <= m * F.lit((1 - similarity) / (1 + similarity) + 1e-9)) & may_reach(similarity, x, y)


def beyond(radius: int, x: str, y: str):
    """Whether two fingerprints lie more than ``radius`` bits apart."""
    return F.bit_count(F.col(f"{x}.fp").bitwiseXOR(F.col(f"{y}.fp"))) > radius


def prefix_leaders(prefix: DataFrame, radius: int, similarity: float) -> DataFrame:
    """Pairs beyond ``radius`` bits of each node with the most typical node (fewest shingles of its own) of each of its prefix shingles."""
    kept = ["node", "fp", "m", *SKETCH_WORDS, "alone"]
    least = prefix.groupBy("item").agg(F.min(F.struct((F.col("alone") / F.col("m")).alias("share"), *kept)).alias("least"), F.count("*").alias("n")).where("n > 1").select("item", "least.*")
    x, y = prefix.alias("x"), least.alias("y")
    pair = x.join(y, (F.col("x.item") == F.col("y.item")) & (F.col("x.node") != F.col("y.node")) & beyond(radius, "x", "y") & may_meet(similarity, "x", "y"))
    return pair.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


def prefix_pairs(prefix: DataFrame, radius: int, similarity: float) -> DataFrame:
    """Pairs ``(a, b)`` of ``prefix(.., root)`` across roots and beyond ``radius`` bits that share a prefix shingle and may have ``similarity``: none that has it is missing."""
    x, y = prefix.alias("x"), prefix.where("inner").alias("y")
    larger = (F.col("x.m") > F.col("y.m")) | ((F.col("x.m") == F.col("y.m")) & (F.col("x.node") > F.col("y.node")))
    pair = x.join(y, (F.col("x.item") == F.col("y.item")) & larger & (F.col("x.root") != F.col("y.root")) & beyond(radius, "x", "y") & may_meet(similarity, "x", "y"))
    return pair.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


def verified(pairs: DataFrame, docs: DataFrame, rid: str, size: int, similarity: float, text: str = "text") -> DataFrame:
    """Pairs of row numbers whose texts' ``size``-word shingle sets have a Jaccard similarity of ``similarity`` or more.

    Pairs are dealt into blocks by both ends, so a text's set travels once a block and not once a pair.
    """
    wanted = pairs.select(F.col("a").alias(rid)).union(pairs.select(F.col("b").alias(rid))).distinct()
    source = docs.join(wanted, rid, "left_semi").select(F.col(rid).alias("rid"), named(text).cast("string").alias("t"))

    def run(batches):
        kind = pa.list_(pa.int64())
        for b in (batch.slice(i, SLICE) for batch in batches for i in range(0, batch.num_rows, SLICE)):
            sets = [shingle_set(t.as_py(), size) for t in b["t"]]
            yield pa.RecordBatch.from_arrays([b["rid"], pa.array(sets, kind)], names=["rid", "sh"])

    sets = cut(source.mapInArrow(run, "rid long, sh array<long>"))
    held, total = sets.agg(F.count("*"), F.coalesce(F.sum(F.size("sh")), F.lit(0))).first()
    blocks = F.lit(max(1, -(-held // BLOCK), -(-total // BLOCK_SHINGLES)))
    of = lambda c: F.pmod(F.xxhash64(c), blocks).cast("int")
    keyed = pairs.select(of("a").alias("ba"), of("b").alias("bb"), "a", "b")
    members = keyed.select(F.col("ba").alias("ka"), F.col("bb").alias("kb"), F.explode(F.array("a", "b")).alias("rid")).distinct().join(sets, "rid")

    def compare(_key, these: pa.Table, held: pa.Table) -> pa.Table:
        column = held["sh"].combine_chunks()
        ends, flat = np.asarray(column.offsets), np.asarray(column.values)
        place = {int(r): flat[ends[i] : ends[i + 1]] for i, r in enumerate(np.asarray(held["rid"]))}
        keep = []
        for a, b in zip(np.asarray(these["a"]), np.asarray(these["b"]), strict=True):
            x, y = place[int(a)], place[int(b)]
            if min(len(x), len(y)) < similarity * max(len(x), len(y)):
                keep.append(False)
                continue
            common = len(np.intersect1d(x, y, assume_unique=True))
            union = len(x) + len(y) - common
            keep.append(union == 0 or common >= similarity * union)
        return these.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return keyed.groupBy("ba", "bb").cogroup(members.groupBy("ka", "kb")).applyInArrow(compare, "a long, b long")


def near_duplicates(docs: DataFrame, radius: int = 3, segments: int = 2, features: str = "shingles", size: int = 3, verify: tuple[int, float] | None = None, doc_id: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame, str]:
    """Class membership ``(rid, doc_id, fp, component_id, keep)`` - one ``keep`` row a class - with the numbered input and its number column."""
    if verify:
        rows, rid = numbered(docs)  # texts are read again by number
    else:
        rid = fresh_name(docs, "rid")
        rows = docs.withColumn(rid, F.monotonically_increasing_id())  # evaluated once
    base = cut(signatures(rows, rid, features, size, doc_id, text, verify[0] if verify else None))
    kind = ["fp", "th"] if verify else ["fp"]
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "rid")).alias("first")
    classes = base.groupBy(*kind).agg(first, F.first("m").alias("m"), F.first("sk").alias("sk"))  # equal texts have equal sketches
    sketch = [F.get("sk", F.lit(i)).alias(c) for i, c in enumerate(SKETCH_WORDS)]
    nodes = classes.select(F.col("first.rid").alias("node"), *kind, "first", *(["m", *sketch] if verify else []))
    if verify:
        nodes = cut(nodes)
        total = nodes.agg(F.coalesce(F.sum("m"), F.lit(0))).first()[0]
        with shuffles_freed(docs.sparkSession):  # shingles and probes are large, what is left of them is small
            prefix = written(prefixes(nodes, shared_shingles(rows, verify[0], total, text), verify[1]), "prefix")
            active = written(prefix.select("node", "fp", "m", *SKETCH_WORDS, "alone").distinct(), "active")
            early = written(near_leaders(active, radius, segments, verify[1]).union(prefix_leaders(prefix, radius, verify[1])).distinct(), "early")
            linked = cut(verified(early, rows, rid, *verify, text))
            roots = cut(components(linked))
            placed = lambda df: df.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
            late = written(near_pairs(placed(active), radius, segments, True, verify[1]).union(prefix_pairs(placed(prefix), radius, verify[1])), "late")
            edges = cut(linked.union(verified(late, rows, rid, *verify, text)))
        release(prefix, active, early, late)
    else:
        edges = near_pairs(nodes.select("node", "fp"), radius, segments)
    member = cut(components(edges))
    linked = member.join(nodes.select("node", "first"), "node")
    heads = linked.groupBy("root").agg(F.min("first").alias("head"))
    heads = member.join(heads, "root").select("node", "head")
    labels = nodes.join(heads, "node", "left").select(*kind, F.coalesce("head", "first").alias("head"))
    out = base.join(labels, kind).select("rid", "doc_id", "fp", F.col("head.doc_id").alias("component_id"), (F.col("rid") == F.col("head.rid")).alias("keep"))
    return out, rows, rid


def drop_near_duplicates(docs: DataFrame, **how) -> DataFrame:
    """One row of each class: the one with the least doc_id. Columns are those of ``docs``."""
    found, rows, rid = near_duplicates(numbered(docs)[0] if not how.get("verify") else docs, **how)
    return rows.join(found.where("keep").select(F.col("rid").alias(rid)), rid, "left_semi").select(*map(named, docs.columns))
