"""Near-miss clones: token bags whose multiset overlap reaches a share of the larger bag.

Identical bags are collapsed first and written once, numbered and with hashed
tokens.  Candidates come from a prefix join: order a bag's token occurrences
(the k-th copy of a token is an item of its own) rarest first; two bags of
sufficient overlap share an item within their first n - ceil(theta * n) + 1.
Items are dealt into groups.  A bag visits the groups of its prefix once each,
with a parity sketch whose bits grow with the bag: two sketches differ in at
most as many places as the bags have unshared items, so pairs that can't reach
the overlap end inside their group and neither they nor bags' tokens travel for
them.  What is left is verified on all tokens.  Tokens are compared by 64-bit
hashes (two of a million distinct ones are equal by chance in 3 of 10^8 tables).
Large inputs are collapsed, proposed and verified in ``ROUNDS`` rounds, by hash
of the bag, group and block; a round's shuffles leave the disk at its end, so
disk holds a share of them at a time and every bag and pair still has its turn.
"""

from __future__ import annotations

import functools
import itertools

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import normalize as N
from . import components as C
from .connections import links_inside

BUCKETS, PARTS = 1 << 20, 64  # counts by hash that order items, and the rows they travel in
GROUP = 1 << 20  # prefix items a group, about
SLICE = 2048  # bags that are turned into prefixes together
CHUNK = 1 << 20  # pairs that are looked at together
ROUNDS = 4  # of an input with more than GROUP tokens or prefix items
LINKS = 1 << 22  # links a group of colours, about
COLOUR = 3 << 20  # tokens a colour of bags whose pairs are all counted, about
TILE = 1024  # bags, or items, of a matrix
PIECE = 1 << 14  # pairs that are written down together
DENSE = 400  # a product of matrices takes as long for an item as counting one of so many pairs
WORDS = 4  # 64-bit words of the smallest sketch


def least_overlap(n, tenths: int):
    """ceil(theta * n) in integers, theta in tenths."""
    return F.floor((n * tenths + 9) / 10).cast("int")


def tokenised(cells: DataFrame, lang: str | None = "en", ignore_below: int = 2, most: int = 500_000_000) -> DataFrame:
    """Cells of one language with comments gone: ``(nb_id, repo, pos, code, sloc, n_tok, bag_id, toks)``; 0-line and too small items leave."""
    c = cells.where(F.col("lang") == lang) if lang else cells
    t = c.withColumn("sloc", N.sloc(F.col("code"))).withColumn("toks", F.explode(F.array(F.sort_array(N.tokens(N.strip_comments(F.col("code"))))))).withColumn("n_tok", F.size("toks"))  # one row of one: else filters cut and sort the text again
    t = t.where((F.col("sloc") > 0) & F.col("n_tok").between(ignore_below, most))
    return t.withColumn("bag_id", F.md5(F.array_join("toks", " ")))


def distinct_bags(tok: DataFrame) -> DataFrame:
    """Identical bags once: ``(bag_id, n_tok, toks, mult)``. A bag travels as its text: no token has a space, and an array takes several times its room."""
    once = tok.groupBy(F.array_join("toks", " ").alias("bag")).agg(F.count("*").alias("mult")).withColumn("toks", F.split("bag", " "))
    return once.select(F.md5("bag").alias("bag_id"), F.size("toks").alias("n_tok"), "toks", "mult")


def rounds_of(total: int) -> int:
    """In how many rounds so many tokens or prefix items are worked on."""
    return ROUNDS if total > GROUP else 1


def united(frames: list[DataFrame]) -> DataFrame:
    return functools.reduce(DataFrame.union, frames)


def collapsed(tok: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Cells without their tokens, and ``stored`` bags. Texts are cut to tokens once; a round's tokens go when its bags are written."""
    spark, parts = tok.sparkSession, ROUNDS
    path = C.folder_for(spark, "tokens")
    t = C.written(tok.withColumn("part", F.pmod(F.xxhash64("bag_id"), F.lit(parts)).cast("int")), "tokens", path, "part")
    kept, known = C.written(t.drop("toks", "part"), "cells"), []
    if rounds_of(C.sums(t, "n_tok")[0]) == 1:
        known.append(stored(distinct_bags(t)))
    else:
        for r in range(parts):
            known.append(stored(distinct_bags(t.where(F.col("part") == r)), r))
            C.delete(spark, f"{path}/part={r}")
    C.delete(spark, path)
    return kept, united(known)


def stored(bags: DataFrame, lot: int = 0) -> DataFrame:
    """``(node, bag_id, n_tok, mult, h)``: bags numbered, with their tokens as ascending hashes, written once. Bags of other lots have other numbers."""
    return C.written(bags.select((F.monotonically_increasing_id() + F.lit(lot << 56)).alias("node"), "bag_id", F.col("n_tok").cast("int").alias("n_tok"), "mult", F.sort_array(F.transform("toks", lambda t: F.xxhash64(t))).alias("h")), "bags")


def flat_items(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """Row number and item of every token of a batch; the k-th copy of a token is an item of its own."""
    ends = np.asarray(column.offsets).astype(np.int64)
    h = np.asarray(column.values)[ends[0] : ends[-1]].view(np.uint64)
    owner = np.repeat(np.arange(len(column)), np.diff(ends))
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
    starts = np.flatnonzero(fresh)
    copy = np.arange(len(h)) - np.repeat(starts, np.diff(np.r_[starts, len(h)]))
    x = h + copy.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(by)
    return owner, x ^ (x >> np.uint64(31))


def item_counts(bags: DataFrame) -> np.ndarray:
    """How many items fall on each of ``BUCKETS`` places: a bounded table that orders items, rare ones first."""
    wide = BUCKETS // PARTS

    def count(batches):
        total = np.zeros(BUCKETS, np.uint32)
        for b in batches:
            total += np.bincount((flat_items(b["h"])[1] >> np.uint64(44)).astype(np.int64), minlength=BUCKETS).astype(np.uint32)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(PARTS, dtype=np.int32)), pa.array([total[i * wide : (i + 1) * wide].tobytes() for i in range(PARTS)], pa.binary())], names=["part", "c"])

    def add(key: tuple, rows: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x.as_py(), np.uint32).astype(np.int64) for x in rows["c"])
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "c": pa.array([np.minimum(total, 2**32 - 1).astype(np.uint32).tobytes()], pa.binary())})

    out = np.zeros(BUCKETS, np.uint32)
    for r in bags.select("h").mapInArrow(count, "part int, c binary").groupBy("part").applyInArrow(add, "part int, c binary").collect():
        out[r.part * wide : (r.part + 1) * wide] = np.frombuffer(r.c, np.uint32)
    return out


def needed(n: np.ndarray, tenths: int) -> np.ndarray:
    """``least_overlap`` of arrays."""
    return (n * tenths + 9) // 10


def level(n: np.ndarray, tenths: int) -> np.ndarray:
    """A sketch has ``WORDS`` words at level 0 and twice as many at each next one, so that unlike bags of any size differ in more places than like ones may."""
    most = 100 * WORDS // (10 - tenths) if tenths < 10 else 400 * WORDS
    return np.ceil(np.log2(np.maximum(n, most) / most)).astype(np.int64)


def sketches(owner: np.ndarray, item: np.ndarray, count: int, words: int) -> np.ndarray:
    """Parities of the items by place, ``words`` 64-bit words a bag; halves united by exclusive or give the sketch of half the words."""
    bits = words * 64
    odd = np.bincount(owner * bits + (item & np.uint64(bits - 1)).astype(np.int64), minlength=count * bits).astype(np.uint8) & 1
    return np.packbits(odd, bitorder="little").view(np.uint64).reshape(count, words)


def _binary(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Values between byte offsets as a binary column."""
    return pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def visits(bags: DataFrame, counts: np.ndarray, groups: int, tenths: int, rounds: int = 1, turn: int = 0) -> DataFrame:
    """``(g, node, n, sk, items, ks)``: a row for each group that holds prefix items of a bag, with those items and their places.

    Of several rounds, one has the groups whose number leaves the remainder ``turn``.
    """
    names = ["g", "node", "n", "sk", "items", "ks"]

    def run(batches):
        for b in (batch.slice(i, SLICE) for batch in batches for i in range(0, batch.num_rows, SLICE)):
            node, n = np.asarray(b["node"]), np.asarray(b["n_tok"]).astype(np.int64)
            owner, item = flat_items(b["h"])
            order = np.lexsort((item, counts[(item >> np.uint64(44)).astype(np.int64)], owner))
            owner, item = owner[order], item[order]
            place = np.arange(len(item)) - (np.cumsum(n) - n)[owner] + 1
            group = ((item >> np.uint64(20)) % np.uint64(groups)).astype(np.int64)
            first = (place <= (n - needed(n, tenths) + 1)[owner]) & (group % rounds == turn)
            levels = level(n, tenths)
            for lv in np.unique(levels):
                here = np.flatnonzero(levels == lv)
                at = np.full(len(n), -1)
                at[here] = np.arange(len(here))
                own = at[owner] >= 0
                sk = sketches(at[owner[own]], item[own], len(here), WORDS << int(lv))
                own &= first
                o, it, k, g = at[owner[own]], item[own], np.minimum(place[own], 65535).astype(np.uint16), group[own]
                if not len(o):
                    continue
                order = np.lexsort((g, o))
                o, it, k, g = o[order], it[order], k[order], g[order]
                starts = np.flatnonzero(np.r_[True, (o[1:] != o[:-1]) | (g[1:] != g[:-1])])
                ends = np.r_[starts, len(o)]
                rows = sk[o[starts]]
                columns = [pa.array(g[starts].astype(np.int32)), pa.array(node[here][o[starts]]), pa.array(n[here][o[starts]].astype(np.int32)), _binary(rows, np.arange(len(rows) + 1) * rows.shape[1] * 8)]
                columns += [_binary((it >> np.uint64(32)).astype(np.uint32), ends * 4), _binary(k, ends * 2)]
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return bags.select("node", "n_tok", "h").mapInArrow(run, "g int, node long, n int, sk binary, items binary, ks binary")


def _joined(column: pa.ChunkedArray, kind) -> np.ndarray:
    """All values of a binary column, one after the other."""
    parts = []
    for c in column.chunks:
        ends = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1]
        parts.append(np.frombuffer(c.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]])
    return np.concatenate(parts).view(kind) if parts else np.zeros(0, kind)


def matcher(tenths: int):
    """Pairs of a group's bags that share an item and whose sizes, places and sketches allow the overlap."""

    def match(rows: pa.Table) -> pa.Table:
        size = np.asarray(rows["n"]).astype(np.int64)
        node, levels = np.asarray(rows["node"]), level(size, tenths)
        found = []
        for lv in np.unique(levels):
            pick, parts = [], []
            for upper in np.unique(levels[levels >= lv]):  # the sketches of larger bags are folded to this level
                at = np.flatnonzero(levels == upper)
                sk = _joined(rows["sk"].take(pa.array(at)), np.uint64).reshape(len(at), WORDS << int(upper))
                for _ in range(int(upper - lv)):
                    half = sk.shape[1] // 2
                    sk = sk[:, :half] ^ sk[:, half:]
                pick.append(at)
                parts.append(sk)
                if needed(size[at].min(), tenths) > size[levels == lv].max():
                    break
            pick, words = np.concatenate(pick), np.ascontiguousarray(np.concatenate(parts).T)
            mine = rows.take(pa.array(pick))
            n, base = size[pick], levels[pick] == lv
            item, k = _joined(mine["items"], np.uint32), _joined(mine["ks"], np.uint16).astype(np.int64)
            owner = np.repeat(np.arange(len(pick)), np.asarray(pc.binary_length(mine["items"])) // 4)
            key = item.astype(np.uint64) << np.uint64(32) | n[owner].astype(np.uint64)
            order = np.argsort(key, kind="stable")
            key, owner, k = key[order], owner[order], k[order]
            last = np.searchsorted(key, (key >> np.uint64(32) << np.uint64(32)) | (n[owner] * 10 // tenths).astype(np.uint64), side="right")
            count = last - np.arange(len(key)) - 1
            total = np.cumsum(count)
            i = 0
            while i < len(key):
                end = max(i + 1, int(np.searchsorted(total, (total[i - 1] if i else 0) + CHUNK, side="right")))
                c = count[i:end]
                x = np.repeat(np.arange(i, end), c)
                y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(c) - c, c)
                i = end
                nx, ny = n[owner[x]], n[owner[y]]  # ny is the larger
                need = needed(ny, tenths)
                fits = (np.minimum(nx - k[x], ny - k[y]) + 1 >= need) & base[owner[x]]
                x, y, room = owner[x[fits]], owner[y[fits]], (nx + ny - 2 * need)[fits]
                apart = np.zeros(len(x), np.int64)
                for w in range(len(words)):
                    apart += np.bitwise_count(words[w, x] ^ words[w, y])
                    if w % WORDS == WORDS - 1:
                        near = apart <= room
                        x, y, room, apart = x[near], y[near], room[near], apart[near]
                a, b = node[pick[x]], node[pick[y]]
                if len(a):
                    found.append(np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1))
        both = np.unique(np.concatenate(found, axis=1), axis=1) if found else np.zeros((2, 0), np.int64)
        return pa.table({"a": both[0], "b": both[1]})

    return match


def candidates(bags: DataFrame, tenths: int = 8) -> DataFrame:
    """Distinct pairs of ``stored`` bags' numbers that share a prefix item and may have the overlap, written once: none that has it is missing."""
    total = C.sums(bags, F.col("n_tok") - least_overlap(F.col("n_tok"), tenths) + 1)[0]
    counts, rounds = item_counts(bags), rounds_of(total)
    groups = max(16 if rounds == 1 else 6 * rounds, -(-total // GROUP))
    seen = [visits(bags, counts, groups, tenths, rounds, r).groupBy("g").applyInArrow(matcher(tenths), "a long, b long").distinct() for r in range(rounds)]
    if rounds == 1:
        return C.written(seen[0], "candidates")
    proposed = [C.written(x, "proposed") for x in seen]
    out = C.written(united(proposed).distinct(), "candidates")
    C.release(*proposed)
    return out


def overlaps(_key, these: pa.Table, held: pa.Table, tenths: int, banded: bool = False) -> pa.Table:
    """Exact overlaps of a block's pairs: a bag's items are marked, then looked up in all its partners at once; ``banded``: and whether a band proposes the pair."""
    ids, size = held["bag_id"].combine_chunks(), np.asarray(held["n_tok"]).astype(np.int64)
    local = np.unique(flat_items(held["h"].combine_chunks())[1], return_inverse=True)[1]
    starts, mark = np.cumsum(size) - size, np.zeros(len(local) + 1, bool)
    node = np.asarray(held["node"])
    order = np.argsort(node)
    a, b = (order[np.searchsorted(node, np.asarray(these[c]), sorter=order)] for c in ("a", "b"))
    order = np.argsort(a, kind="stable")
    a, b = a[order], b[order]
    overlap = np.zeros(len(a), np.int64)
    cuts = np.flatnonzero(np.r_[True, a[1:] != a[:-1], True])
    for i, j in zip(cuts[:-1], cuts[1:], strict=True):
        mine = local[starts[a[i]] : starts[a[i]] + size[a[i]]]
        mark[mine] = True
        many = size[b[i:j]]
        begin = np.cumsum(many) - many
        overlap[i:j] = np.add.reduceat(mark[local[np.repeat(starts[b[i:j]] - begin, many) + np.arange(many.sum())]].astype(np.int64), begin)
        mark[mine] = False
    most = np.maximum(size[a], size[b])
    keep = overlap >= needed(most, tenths)
    a, b, overlap, most = a[keep], b[keep], overlap[keep], most[keep]
    out = {"x": node[a], "y": node[b], "ida": ids.take(pa.array(a)), "idb": ids.take(pa.array(b)), "overlap": overlap.astype(np.int32), "sim": overlap / most}
    if banded:
        used, places = np.unique(np.concatenate([a, b]), return_inverse=True)
        keys, (a, b) = band_keys(held["h"].combine_chunks().take(pa.array(used))), places.reshape(2, -1)
        out["proposed"] = np.concatenate([(keys[a[i : i + SLICE]] == keys[b[i : i + SLICE]]).any(axis=1) for i in range(0, max(1, len(a)), SLICE)])
    return pa.table(out)


def among(bags: DataFrame, ends: DataFrame) -> DataFrame:
    """Bags whose numbers are in ``ends(node)``: marked in bitmaps, a bit for each bag's place, so that no other bag travels."""
    place, bit = F.bitmap_bucket_number("node").alias("bucket"), F.bitmap_bit_position("node")
    marks = ends.groupBy(place).agg(F.bitmap_construct_agg(bit).alias("marks"))
    byte = F.expr("cast(conv(hex(substring(marks, cast(bit div 8 AS int) + 1, 1)), 16, 10) AS int)")
    seen = bags.select("*", place, bit.cast("int").alias("bit")).join(F.broadcast(marks), "bucket")
    return seen.where(F.getbit(byte, F.col("bit") % 8) == 1).drop("bucket", "bit", "marks")


def verify(cand: DataFrame, bags: DataFrame, tenths: int = 8, banded: bool = False) -> DataFrame:
    """``(a, b, overlap, sim, x, y)``, written once, of candidates that reach the overlap, by the ids of bags (a < b) and by their numbers; with ``banded`` also ``proposed``.

    A pair is dealt to the block of the least neighbour of one end, so bags that are alike meet in few blocks and
    their tokens travel once a block and not once a pair.
    """
    total = C.sums(bags, "n_tok")[0]
    blocks, rounds = max(16, -(-total // GROUP)), rounds_of(total)
    least = cand.select("a", "b").union(cand.select("b", "a")).groupBy("a").agg(F.least("a", F.min("b")).alias("least"))
    dealt = C.written(cand.join(least, "a").select(F.pmod(F.xxhash64("least"), F.lit(blocks)).cast("int").alias("g"), "a", "b"), "blocks")

    def compare(key, these: pa.Table, held: pa.Table) -> pa.Table:
        return overlaps(key, these, held, tenths, banded)

    out = []
    for r in range(rounds):
        keyed = dealt.where(F.col("g") % rounds == r)
        ends = keyed.select(F.col("g").alias("block"), F.explode(F.array("a", "b")).alias("node"))
        members = ends.distinct().join(among(bags, ends), "node").select("block", "node", "bag_id", "n_tok", "h")
        found = keyed.groupBy("g").cogroup(members.groupBy("block")).applyInArrow(compare, "x long, y long, ida string, idb string, overlap int, sim double" + ", proposed boolean" * banded)
        out.append(C.written(found.select(F.least("ida", "idb").alias("a"), F.greatest("ida", "idb").alias("b"), "overlap", "sim", "x", "y", *["proposed"] * banded), "pairs"))
    C.release(dealt)
    return united(out)


def pairs(bags: DataFrame, tenths: int = 8, method: str = "prefix") -> DataFrame:
    """All cross-bag pairs at theta = tenths / 10; ``lsh`` proposes by banded minima instead (recall below 1)."""
    return numbered_pairs(stored(bags), tenths, method)


def numbered_pairs(known: DataFrame, tenths: int = 8, method: str = "prefix", banded: bool = False) -> DataFrame:
    """``pairs`` of ``stored`` bags, written once; ``banded``: with ``proposed``, whether ``lsh`` has the pair, seen where both bags meet anyhow."""
    found = candidates(known, tenths) if method == "prefix" else C.written(lsh_candidates(known), "candidates")
    out = verify(found, known, tenths, banded)
    C.release(found)
    return out


def band_keys(column: pa.ListArray, bands: int = 24, rows: int = 3) -> np.ndarray:
    """A row of keys a bag, each of ``rows`` MinHash minima."""
    keys = np.zeros((len(column), bands), np.uint64)
    for i in range(0, len(column), SLICE):
        owner, item = flat_items(column.slice(i, SLICE))
        starts, own = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]]), keys[i : i + SLICE]
        for s in range(bands * rows):
            x = (item ^ (np.uint64(s + 1) * np.uint64(0x9E3779B9))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(32))) * np.uint64(0x94D049BB133111EB)
            own[:, s // rows] = (own[:, s // rows] + np.minimum.reduceat(x ^ (x >> np.uint64(29)), starts) + np.uint64(s)) * np.uint64(0x9FB21C651E98DF25)
    return keys


def lsh_candidates(bags: DataFrame, bands: int = 24, rows: int = 3) -> DataFrame:
    """Pairs of ``stored`` bags' numbers that agree in a band of MinHash minima: one narrow pass, an equi-join on the band."""

    def run(batches):
        for b in (batch.slice(i, SLICE) for batch in batches for i in range(0, batch.num_rows, SLICE)):
            keys = band_keys(b["h"], bands, rows)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.asarray(b["node"]), bands)), pa.array(keys.reshape(-1).view(np.int64))], names=["node", "key"])

    keys = bags.select("node", "h").mapInArrow(run, "node long, key long")
    x, y = keys.select("key", F.col("node").alias("a")), keys.select("key", F.col("node").alias("b"))
    return x.join(y, "key").where("a < b").select("a", "b").distinct()


def spans(starts: np.ndarray, many: np.ndarray) -> np.ndarray:
    """The numbers from each start on, ``many`` of them, one list after the other."""
    return np.repeat(starts - (np.cumsum(many) - many), many) + np.arange(many.sum())


def shared_counts(x: tuple, y: tuple, place: np.ndarray) -> np.ndarray:
    """Sums of least counts of each bag of tile ``x`` with each of tile ``y``, both ``(bags, items, times, starts, rows)``; ``place``: where ``y`` has an item.

    Items that many bags of both have are counted by a product of 0/1 matrices, the others pair by pair; both are exact.
    """
    (nx, items, dx, sx, rx), (ny, _, dy, sy, ry) = x, y
    at = np.flatnonzero(place[items] >= 0)
    to = place[items[at]]
    dx, sx, dy, sy = dx[at], sx[at], dy[to], sy[to]
    heavy = dx * dy > nx * ny // DENSE
    light, sums = np.flatnonzero(~heavy), np.zeros(nx * ny, np.int64)
    many, first = np.repeat(dy[light], dx[light]), rx[spans(sx[light], dx[light])] * ny
    upto = np.cumsum(many)
    start, total = np.repeat(sy[light], dx[light]) - (upto - many), int(many.sum())
    cuts = np.unique(np.r_[np.searchsorted(upto, np.arange(0, total, PIECE)), len(many)])
    keys = np.empty(min(total, 2 * CHUNK + PIECE + ny), np.int64)
    done = filled = 0
    for i, j in itertools.pairwise(cuts):  # pieces that stay in the processor's caches
        c, end = many[i:j], int(upto[j - 1])
        piece = ry[np.repeat(start[i:j], c) + np.arange(done, end)]
        piece += np.repeat(first[i:j], c)
        keys[filled : filled + len(piece)] = piece
        done, filled = end, filled + len(piece)
        if filled >= 2 * CHUNK or end == total:
            sums += np.bincount(keys[:filled], minlength=nx * ny)
            filled = 0
    sums, heavy = sums.reshape(nx, ny), np.flatnonzero(heavy)
    for i in range(0, len(heavy), TILE):
        own = heavy[i : i + TILE]
        a, b = np.zeros((nx, len(own)), np.float32), np.zeros((ny, len(own)), np.float32)
        for matrix, rows, starts, many in ((a, rx, sx[own], dx[own]), (b, ry, sy[own], dy[own])):
            matrix[rows[spans(starts, many)], np.repeat(np.arange(len(own)), many)] = 1
        sums += (a @ b.T).astype(np.int64)  # at most TILE, which is exact
    return sums


def run_lengths(batches):
    """Sorted tokens of a bag once each, as text, and how often it has them."""
    for b in (batch.slice(i, SLICE) for batch in batches for i in range(0, batch.num_rows, SLICE)):
        split = pc.split_pattern(b["bag"], " ")
        flat, ends = split.flatten(), np.asarray(split.offsets).astype(np.int64)
        ends -= ends[0]
        fresh = np.ones(len(flat), bool)
        fresh[1:] = np.asarray(pc.not_equal(flat[1:], flat[:-1]).cast(pa.uint8())).astype(bool)
        fresh[ends[:-1]] = True
        starts = np.flatnonzero(fresh)
        words = pa.ListArray.from_arrays(pa.array(np.searchsorted(starts, ends).astype(np.int32)), flat.take(pa.array(starts)))
        times = np.diff(np.r_[starts, len(flat)]).astype(np.int32)
        yield pa.RecordBatch.from_arrays([b["bag_id"], b["n_tok"], pc.binary_join(words, " "), _binary(times, np.asarray(words.offsets).astype(np.int64) * 4)], names=["bag_id", "n_tok", "words", "times"])


def all_overlaps(rows: pa.Table, tenths: int, two: bool) -> pa.Table:
    """Pairs that reach the overlap, of all pairs between ``two`` colours, one of which may be empty, or inside the only one; nothing but the overlap itself decides."""
    colour, ids, n = np.asarray(rows["colour"]), rows["bag_id"].combine_chunks(), np.asarray(rows["n_tok"])
    order = np.lexsort((n, colour))
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    n, split = n[order], pc.split_pattern(rows["words"].combine_chunks(), " ")
    code = np.asarray(split.flatten().dictionary_encode().indices)
    times = _joined(rows["times"], np.int32).astype(np.int64)
    most = np.zeros(int(code.max()) + 1, np.int64)
    np.maximum.at(most, code, times)
    item = spans((np.cumsum(most) - most)[code], times)  # the k-th copy of a token is an item of its own
    owner = np.repeat(np.repeat(rank, np.diff(np.asarray(split.offsets))), times)
    held = np.bincount(item) > 1
    own = held[item]  # what one bag alone has is in no pair
    item, owner, count = (np.cumsum(held) - 1)[item[own]], owner[own], int(held.sum())
    first = int((colour == colour.min()).sum())
    cuts = [*range(0, first, TILE), *range(first, len(n), TILE), len(n)]
    place = np.concatenate([t * count * TILE + np.arange(hi - lo) for t, (lo, hi) in enumerate(itertools.pairwise(cuts))])
    key = np.sort(item * TILE + place[owner])
    limits = np.searchsorted(key, np.arange(len(cuts)) * count * TILE)
    tiles = []
    for t, (lo, hi) in enumerate(itertools.pairwise(limits)):
        its, at = np.divmod(key[lo:hi] - t * count * TILE, TILE)
        starts = np.flatnonzero(np.r_[True, its[1:] != its[:-1]]) if len(its) else np.zeros(0, np.int64)
        tiles.append((cuts[t + 1] - cuts[t], its[starts], np.diff(np.r_[starts, len(its)]), starts, at))
    need, found, place = needed(n, tenths), [np.zeros((3, 0), np.int64)], np.empty(count, np.int64)
    for t, y in enumerate(tiles):
        if two and cuts[t] < first:
            continue
        place[:] = -1
        place[y[1]] = np.arange(len(y[1]))
        for u, x in enumerate(tiles[: t + 1]):
            if two and cuts[u] >= first:
                break
            sums = shared_counts(x, y, place)
            near = sums >= np.maximum.outer(need[cuts[u] : cuts[u + 1]], need[cuts[t] : cuts[t + 1]])
            a, b = np.nonzero(np.triu(near, 1) if u == t else near)
            found.append(np.stack([a + cuts[u], b + cuts[t], sums[a, b]]))
    a, b, overlap = np.concatenate(found, axis=1)
    return pa.table({"ida": ids.take(pa.array(order[a])), "idb": ids.take(pa.array(order[b])), "overlap": overlap.astype(np.int32), "sim": overlap / np.maximum(n[a], n[b])})


def meetings(known: DataFrame, rounds: int, turn: int) -> DataFrame:
    """``known`` with ``g`` and ``colour``: bags of 2 * rounds colours in the two groups that each colour visits in a round; two colours have one group in one round."""
    colours, other = 2 * rounds, F.pmod(F.lit(turn) - F.col("colour"), F.lit(rounds))
    dealt = known.withColumn("colour", F.pmod(F.xxhash64("bag_id"), F.lit(colours)).cast("int")).withColumn("other", F.explode(F.array(other, other + rounds)))
    return dealt.withColumn("g", F.least("colour", "other") * F.lit(colours).cast("long") + F.greatest("colour", "other")).drop("other")


def brute_force(bags: DataFrame, tenths: int = 8) -> DataFrame:
    """Reference without any filter, written once: sums of least counts over every token, of every pair of bags.

    Bags are dealt into colours, and a group has all pairs of two colours (or of one), which are counted where they
    meet: only bags travel, as text, and tokens are compared as such.  In a round a bag visits two groups, so disk
    holds two copies of the bags at a time, whatever the number of pairs that share a token.
    """
    texts = bags.where(F.size("toks") > 0).select("bag_id", F.col("n_tok").cast("long").alias("n_tok"), F.array_join(F.sort_array("toks"), " ").alias("bag"))
    known = C.written(texts.mapInArrow(run_lengths, "bag_id string, n_tok long, words string, times binary"), "bags")
    rounds = max(1, -(-C.sums(known, "n_tok")[0] // (2 * COLOUR)))
    colours, out = 2 * rounds, []

    def count(key: tuple, rows: pa.Table) -> pa.Table:
        one, other = divmod(key[0].as_py(), colours)
        return all_overlaps(rows, tenths, one != other)

    for r in range(rounds):
        found = meetings(known, rounds, r).repartition(4 * colours, "g").groupBy("g").applyInArrow(count, "ida string, idb string, overlap int, sim double")
        out.append(C.written(found.select(F.least("ida", "idb").alias("a"), F.greatest("ida", "idb").alias("b"), "overlap", "sim"), "pairs"))
    C.release(known)
    return united(out)


def flags(tok: DataFrame, bags: DataFrame, found: DataFrame) -> DataFrame:
    """Tokenised cells with ``is_clone``: the bag repeats or has a neighbour; ``bags(bag_id, mult)``."""
    linked = found.select(F.explode(F.array("a", "b")).alias("bag_id")).distinct().withColumn("linked", F.lit(True))
    state = bags.join(linked, "bag_id", "left").select("bag_id", (F.coalesce("linked", F.lit(False)) | (F.col("mult") > 1)).alias("is_clone"))
    return tok.drop("toks").join(state, "bag_id")


def bag_counts(tok: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """``(nb_id, repo, bag_id, n)``; with ``stored`` bags, bag_id is their number."""
    counts = tok.groupBy("nb_id", "repo", "bag_id").agg(F.count("*").alias("n"))
    return counts if known is None else counts.join(known.select("bag_id", "node"), "bag_id").select("nb_id", "repo", F.col("node").alias("bag_id"), "n")


def self_clones(counts: DataFrame, found: DataFrame) -> DataFrame:
    """Notebooks with a near-miss pair inside."""
    return counts.where("n > 1").select("nb_id").union(links_inside(found, counts).select("nb_id")).distinct()


def sanitise(lines: DataFrame, value: str = "value") -> tuple[DataFrame, DataFrame]:
    """Pair lines to integers: only digits and commas stay, four integers a line, repeats go; and a count of each step."""
    clean = lines.select(F.col(value), F.regexp_replace(value, "[^0-9,]", "").alias("v"))
    parts = clean.withColumn("p", F.split("v", ",")).withColumn("ok", (F.size("p") == 4) & F.forall("p", lambda x: x != ""))
    good = parts.where("ok").select("v", *[F.expr(f"try_cast(p[{i}] AS BIGINT)").alias(c) for i, c in enumerate(("p1", "f1", "p2", "f2"))])
    unique = good.dropDuplicates(["v"]).drop("v")
    report = parts.agg(F.count("*").alias("lines"), F.count_if(F.col("v") != F.col(value)).alias("polluted"), F.count_if(~F.col("ok")).alias("malformed"), F.count_if("ok").alias("kept"), F.count_distinct(F.when(F.col("ok"), F.col("v"))).alias("unique_lines"))
    return unique, report


def triangles(edges: DataFrame) -> DataFrame:
    """``(g, n)``: triangles of a table of links ``(u, v)``, each once, by groups of three colours of their ends.

    A link goes to the groups of its two colours and any third, so links travel once a colour; wedges are made and closed
    inside a group, a chunk at a time, and never travel.
    """
    k = min(30, max(4, int(np.ceil((9 * edges.count() / LINKS) ** 0.5))))
    third = F.array(*[F.lit(4**i).cast("long") for i in range(k)])  # sums of three tell which colours they are
    of = lambda c: F.get(third, F.pmod(F.xxhash64(c), F.lit(k)).cast("int"))
    dealt = edges.select("u", "v", of("u").alias("cu"), of("v").alias("cv")).select(F.explode(F.transform(third, lambda c: F.col("cu") + F.col("cv") + c)).alias("g"), "u", "v", "cu", "cv")

    def count(key: tuple, rows: pa.Table) -> pa.Table:
        group, m = key[0].as_py(), rows.num_rows
        ends = pa.concat_arrays([rows[c].combine_chunks() for c in ("u", "v")]).dictionary_encode().indices
        u, v = np.asarray(ends).astype(np.int64).reshape(2, m)
        nodes = int(max(u.max(), v.max())) + 1
        colour = np.zeros(nodes, np.int64)
        colour[u], colour[v] = np.asarray(rows["cu"]), np.asarray(rows["cv"])
        order = np.lexsort((v, u))
        u, v = u[order], v[order]
        known = np.sort(np.minimum(u, v) * nodes + np.maximum(u, v))
        many = np.searchsorted(u, u, side="right") - np.arange(m) - 1  # later links of the same node
        upto, i, n = np.cumsum(many), 0, 0
        while i < m:
            end = max(i + 1, int(np.searchsorted(upto, (upto[i - 1] if i else 0) + CHUNK, side="right")))
            c = many[i:end]
            x = np.repeat(np.arange(i, end), c)
            y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(c) - c, c)
            i = end
            own = colour[u[x]] + colour[v[x]] + colour[v[y]] == group  # others are counted in the group of their colours
            a, b = v[x[own]], v[y[own]]
            sought = np.minimum(a, b) * nodes + np.maximum(a, b)
            n += int((known[np.minimum(np.searchsorted(known, sought), m - 1)] == sought).sum())
        return pa.table({"g": pa.array([group], pa.int64()), "n": pa.array([n], pa.int64())})

    return dealt.groupBy("g").applyInArrow(count, "g long, n long")


def open_triples(found: DataFrame) -> DataFrame:
    """Count of a~b, b~c without a~c: the relation isn't transitive."""
    ends = found.select(F.explode(F.array("a", "b")).alias("x")).groupBy("x").agg(F.count("*").alias("d"))
    wedges = ends.agg(F.coalesce(F.sum(F.col("d") * (F.col("d") - 1) / 2), F.lit(0)).cast("long").alias("wedges"))
    # links point to the end of more links: no node has more than the root of twice the links
    known = found.join(ends.toDF("a", "da"), "a").join(ends.toDF("b", "db"), "b")
    up = (F.col("da") < F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") < F.col("b")))
    edge = known.select(F.when(up, F.col("a")).otherwise(F.col("b")).alias("u"), F.when(up, F.col("b")).otherwise(F.col("a")).alias("v"))
    closed = triangles(C.written(edge, "links")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))
    return wedges.crossJoin(closed).select((F.col("wedges") - 3 * F.col("triangles")).alias("open_triples"))  # one row each


def components(found: DataFrame) -> DataFrame:
    """``(bag_id, root)``: least reachable bag, by star contraction until nothing changes; an upper bound, not a clone group."""
    return C.components(found).select(F.col("node").alias("bag_id"), "root")
