"""N-gram Jaccard join by size-banded tiles with hashed bitmap signatures.

Every text becomes the set of its word n-grams (64-bit hashes, sorted). Texts with equal sets are one class. A class
puts the rarest part of its set - long enough that two classes over the threshold share one entry - into tiles. A tile is
named by shingle, size band and two blocks of members: it holds the sets of its band, and as guests the smaller sets that can
reach the threshold with one of them; the larger set of a pair is never a guest, so a pair has one tile for each shingle it
shares. A parity bitmap of each set bounds the overlap of a pair from above; what passes is decided by the exact
intersection of the sorted arrays. Components come first: pairs that are connected already through verified links are not
compared again, so a group of n near copies costs about n comparisons. The links of each class are then counted within its
component, in tiles of two blocks, by exact products of incidence matrices; no stage emits the pairs of a group unless they are
asked for.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, blocks, discard, map_batches, map_stream, materialise, may_contain, membership_filter, mix, passes, span_hashes, utf8, word_spans
from .components import components

#: Slots of the frequency sketch that orders shingles from rare to common: 2 MiB whatever the input.
SKETCH_BITS = 18
#: Members of a tile's block; a tile compares two blocks.
TILE = 512
#: Rows of one shingle that a worker holds at a time, and that go to one task when the shingle's slot of the sketch stands out.
PIECE = 1 << 16
#: Members of a component's block where its links are counted; the sets of two blocks meet.
GROUP = 256


def shingle_sets(col: pa.Array, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text: ``width`` consecutive words, or all words of a shorter text."""
    data, offsets, _ = utf8(col)
    m = np.uint64(0xD1342543DE82EF95)
    for i, j in blocks(offsets):
        off = offsets[i : j + 1] - offsets[i]
        raw = LOWER[data[offsets[i] : offsets[j]]]
        starts, ends, doc = word_spans(raw, off)
        w = span_hashes(raw, starts, ends)
        n = max(len(w) - width + 1, 0)
        sh = w[:n].copy()
        for k in range(1, width):
            sh = sh * m + w[k : n + k]
        sh = mix(sh + np.uint64(width))
        first = np.searchsorted(doc, np.arange(j - i + 1))
        for d in range(j - i):
            a, b = int(first[d]), int(first[d + 1])
            if b - a >= width:
                yield np.unique(sh[a : b - width + 1])
            elif b > a:
                h = w[a]
                for k in range(a + 1, b):
                    h = np.uint64((int(h) * int(m) + int(w[k])) & 0xFFFFFFFFFFFFFFFF)
                yield mix(np.array([h], np.uint64) + np.uint64(b - a))
            else:
                yield np.zeros(0, np.uint64)


def parity_bitmap(s: np.ndarray) -> bytes:
    """One bit for each hash slot: whether an odd number of members fell there. The bits in which two bitmaps differ
    never outnumber the members in which the sets differ."""
    size = min(8192, max(64, 1 << int(2 * len(s) - 1).bit_length()))
    return np.packbits((np.bincount((s & np.uint64(size - 1)).astype(np.int64), minlength=size) & 1).astype(np.uint8), bitorder="little").tobytes()


_POP = np.array([bin(i).count("1") for i in range(256)], np.uint16)


def _folded(bitmap: bytes, size: int) -> np.ndarray:
    """A parity bitmap of ``size`` bytes: the upper half of a longer one is folded onto the lower by exclusive or."""
    x = np.frombuffer(bitmap, np.uint8)
    while len(x) > size:
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    return x


def bound_passes(na, nb, differ, percent: int) -> np.ndarray:
    """Whether sets of na and nb members that differ in at least ``differ`` can reach the threshold (exact integers)."""
    total = np.asarray(na, np.int64) + nb
    most = (total - differ) // 2
    return (100 * most >= percent * (total - most)) & (100 * np.minimum(na, nb) >= percent * np.maximum(na, nb))


def frequency_sketch(docs: DataFrame, width: int) -> np.ndarray:
    """How many sets hold a shingle of each hash slot, over all texts; the driver gets 2**SKETCH_BITS numbers."""
    parts, slots = 64, 1 << SKETCH_BITS

    def count(batches):
        acc = np.zeros(slots, np.int64)
        for b in batches:
            for s in shingle_sets(b.column(0), width):
                np.add.at(acc, (s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), 1)
        size = slots // parts
        for p in range(parts):
            x = acc[p * size : (p + 1) * size]
            at = np.flatnonzero(x)
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([at.astype(np.int32)], pa.list_(pa.int32())), pa.array([x[at]], pa.list_(pa.int64()))], ["part", "at", "n"])

    def add(key, t):
        acc = np.zeros(slots // parts, np.int64)
        for b in t.to_batches():
            np.add.at(acc, b.column("at").flatten().to_numpy(), b.column("n").flatten().to_numpy())
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "n": pa.array([acc], pa.list_(pa.int64()))})

    rows = map_stream(docs.select("text"), count, "part int, at array<int>, n array<long>").groupBy("part").applyInArrow(add, "part int, n array<long>").collect()
    out = np.zeros(slots, np.int64)
    for r in rows:
        out[r["part"] * (slots // parts) : (r["part"] + 1) * (slots // parts)] = r["n"]
    return out


def signatures(docs: DataFrame, sketch: np.ndarray, width: int, percent: int) -> DataFrame:
    """One row per text: (id, n, h1, h2, bitmap, tokens, early); h1 and h2 name the set, tokens are its rarest shingles."""
    mean = max(1.0, sketch.mean())
    level = np.clip(4 * np.log2(np.maximum(sketch, 1) / mean), 2, 250).astype(np.uint8)  # common slots come last, the rest by hash

    def sign(b: pa.RecordBatch) -> pa.RecordBatch:
        n, h1, h2, maps, tokens, early = [], [], [], [], [], []
        for s in shingle_sets(b.column("text"), width):
            n.append(len(s))
            if len(s):
                h1.append(int(mix(s * np.uint64(0x9E3779B97F4A7C15)).sum(dtype=np.uint64).view(np.int64)))
                h2.append(int(np.bitwise_xor.reduce(mix(s + np.uint64(0xA0761D6478BD642F))).view(np.int64)))
                maps.append(parity_bitmap(s))
                keep = len(s) - (percent * len(s) + 99) // 100 + 1
                lv = level[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
                tokens.append(s[np.argsort(lv, kind="stable")[:keep]].view(np.int64))
                # a pair over the threshold shares a token that stands within this many of its smaller set
                early.append(len(s) - -(-2 * percent * len(s) // (100 + percent)) + 1)
            else:
                h1.append(None), h2.append(None), maps.append(None), tokens.append(None), early.append(None)
        return pa.RecordBatch.from_arrays(
            [b.column("id").cast(pa.int64()), pa.array(n, pa.int64()), pa.array(h1, pa.int64()), pa.array(h2, pa.int64()), pa.array(maps, pa.binary()), pa.array(tokens, pa.list_(pa.int64())), pa.array(early, pa.int32())],
            ["id", "n", "h1", "h2", "bitmap", "tokens", "early"],
        )

    return materialise(map_batches(docs, sign, "id long, n long, h1 long, h2 long, bitmap binary, tokens array<long>, early int"), "signatures")


def _dealt_tokens(owners: DataFrame, sketch: np.ndarray) -> DataFrame:
    """(token, id, n, early, salt): the tokens of all classes. Tokens of sketch slots that stand far above the mean are cut by the
    hash of the id, so that a token with a large share of all rows goes to many tasks; at most half of the slots can stand
    above twice the mean, so what is broadcast is bounded (2**17 rows), whatever the input."""
    tokens = owners.select("id", "n", "early", F.posexplode("tokens").alias("at", "token")).select("token", "id", "n", (F.col("at") < F.col("early")).cast("long").alias("early"))
    over = sketch - 2 * sketch.mean()
    hot = np.flatnonzero(over > PIECE)
    if not len(hot):
        return tokens.withColumn("salt", F.lit(-1).cast("long"))
    cuts = owners.sparkSession.createDataFrame([(int(h), int(over[h] // PIECE) + 1) for h in hot], "slot long, cuts long")
    salted = tokens.withColumn("slot", F.shiftrightunsigned("token", 64 - SKETCH_BITS)).join(F.broadcast(cuts), "slot", "left")
    return salted.select("token", "id", "n", "early", F.coalesce(F.pmod(F.xxhash64("id"), F.col("cuts")), F.lit(-1)).alias("salt"))


def _shared_tokens(owners: DataFrame, sketch: np.ndarray, percent: int) -> DataFrame:
    """(token, id, n, early, leader, partner) of tokens that two or more classes hold; early: the token counts for the smaller
    set. Members of a token, by size, follow a leader of nearly their size, and each is paired with one more member in an order
    that every token shuffles anew: as many pairs as rows, which connect most of each group in the first round. A worker holds
    at most PIECE rows and a batch: a longer token, or a cut one, is led and paired piece by piece."""

    def runs(batches):
        rest, split = None, None  # split: the token and salt of which a piece has been sent on
        for b in batches:
            t = np.column_stack([b.column(i).to_numpy() for i in range(5)])
            t = t if rest is None else np.concatenate([rest, t])
            last = np.flatnonzero((t[:, [0, 4]] != t[-1, [0, 4]]).any(1))
            cut = int(last[-1]) + 1 if len(last) else 0
            yield from emit(t[:cut], split)
            rest = t[cut:]
            if len(rest) > PIECE:
                split = tuple(rest[0, [0, 4]])
                yield from emit(rest, split)
                rest = None
        if rest is not None:
            yield from emit(rest, split)

    def emit(t, split):
        if not len(t):
            return
        first = np.flatnonzero(np.r_[True, (t[1:, [0, 4]] != t[:-1, [0, 4]]).any(1)])
        size = np.diff(np.r_[first, len(t)])
        part = t[first, 4] >= 0  # pieces of a longer token: their other members are elsewhere
        if split:
            part |= (t[first, 0] == split[0]) & (t[first, 4] == split[1])
        keep = part | ((size > 1) & (np.add.reduceat(t[:, 3], first) > 0))
        t = t[np.repeat(keep, size)]
        if not len(t):
            return
        t = t[np.lexsort((t[:, 1], t[:, 2], t[:, 0]))]
        lead, at = np.empty(len(t), np.int64), None
        tok, n = t[:, 0].tolist(), t[:, 2].tolist()
        for i in range(len(t)):
            if at is None or tok[i] != tok[at] or 100 * n[at] < percent * n[i]:
                at = i
            lead[i] = at
        order = np.lexsort((mix(t[:, 1].astype(np.uint64) ^ mix(t[:, 0].astype(np.uint64))), t[:, 0]))
        partner = t[:, 1].copy()
        same = t[order[1:], 0] == t[order[:-1], 0]
        partner[order[:-1][same]] = t[order[1:][same], 1]
        yield pa.RecordBatch.from_arrays([pa.array(t[:, 0]), pa.array(t[:, 1]), pa.array(t[:, 2]), pa.array(t[:, 3] > 0), pa.array(t[lead, 1]), pa.array(partner)], ["token", "id", "n", "early", "leader", "partner"])

    parts = int(owners.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = _dealt_tokens(owners, sketch).repartition(parts, "token", "salt").sortWithinPartitions("token", "salt")
    return materialise(map_stream(dealt, runs, "token long, id long, n long, early boolean, leader long, partner long"), "tiles")


def _verified(docs: DataFrame, owners: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) that reach the threshold: bitmaps first, then exact intersections of the sorted arrays."""
    side = owners.select("id", "n", "bitmap")
    near = pairs.join(side.toDF("a", "na", "ma"), "a").join(side.toDF("b", "nb", "mb"), "b")

    def screen(b: pa.RecordBatch):
        ma, mb = b.column("ma").to_pylist(), b.column("mb").to_pylist()
        differ = np.empty(len(ma), np.int64)
        for i, (x, y) in enumerate(zip(ma, mb, strict=True)):
            size = min(len(x), len(y))
            differ[i] = _POP[_folded(x, size) ^ _folded(y, size)].sum()
        keep = bound_passes(b.column("na").to_numpy(), b.column("nb").to_numpy(), differ, percent)
        return b.select(["a", "b"]).filter(pa.array(keep))

    near = materialise(map_batches(near, screen, "a long, b long"), "candidates")
    ends = near.select(F.col("a").alias("id")).union(near.select(F.col("b").alias("id"))).distinct()
    bits = membership_filter(ends, "id")

    def sets(b: pa.RecordBatch):
        live = np.flatnonzero(passes(bits, b.column("slot").to_numpy()))
        if not len(live):
            return None
        b = b.take(pa.array(live))
        return pa.RecordBatch.from_arrays([b.column("id").cast(pa.int64()), pa.array([s.view(np.int64) for s in shingle_sets(b.column("text"), width)], pa.list_(pa.int64()))], ["id", "s"])

    have = map_batches(docs.where("id is not null").select("id", "text", may_contain("id").alias("slot")), sets, "id long, s array<long>")
    have = materialise(have.join(ends, "id", "left_semi"), "sets")

    def decide(b: pa.RecordBatch):
        keep = []
        for x, y in zip(b.column("sa"), b.column("sb"), strict=True):
            x, y = x.values.to_numpy(), y.values.to_numpy()
            if len(x) > len(y):
                x, y = y, x
            x, y = x.view(np.uint64), y.view(np.uint64)
            at = np.searchsorted(y, x)
            common = int((y[np.minimum(at, len(y) - 1)] == x).sum()) if len(y) else 0
            keep.append(100 * common >= percent * (len(x) + len(y) - common))
        return b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    joined = near.join(have.toDF("a", "sa"), "a").join(have.toDF("b", "sb"), "b")
    links = materialise(map_batches(joined, decide, "a long, b long"), "links")
    discard(near, have)
    return links


def _halved(owners: DataFrame) -> DataFrame:
    """Bitmaps folded once for the tiles, where they only screen: half the bytes, and still about a bit for each member."""

    def fold_once(b: pa.RecordBatch) -> pa.RecordBatch:
        maps = [_folded(m, max(8, len(m) // 2)).tobytes() for m in b.column(1).to_pylist()]
        return pa.RecordBatch.from_arrays([b.column(0), pa.array(maps, pa.binary())], ["id", "bitmap"])

    return map_batches(owners.select("id", "bitmap"), fold_once, "id long, bitmap binary")


def size_band(n):
    """The band of a set's size, as a Spark column: sizes of one band differ by less than a factor of four."""
    return ((F.length(F.bin(n)) - 1) / 2).cast("int")


def _cross_pairs(tiles: DataFrame, owners: DataFrame, labels: DataFrame, percent: int) -> DataFrame:
    """Pairs of a tile that their bitmaps admit and that are not connected yet. Each row stands in the tile of its
    own band and, as a guest, in those of larger sets within the threshold. A token of m members in a band is cut into blocks
    by hash, m / TILE of them; a tile meets two blocks, by size, and ends where sizes are too far apart. The cut bounds a
    task's memory, not the work: each row is copied m / TILE times and, where the members are not connected, about m * m / 2
    bitmaps are compared, as many as there may be links."""
    rows = tiles.select("token", "id", "n", "early")
    rows = rows.join(labels.toDF("id", "label"), "id", "left").select("token", "id", "n", "early", F.coalesce("label", "id").alias("label"))
    most = F.expr(f"n * 100 div {int(percent)}")
    rows = rows.withColumn("band", F.explode(F.sequence(size_band(F.col("n")), size_band(most)))).withColumn("home", F.col("band") == size_band(F.col("n")))
    # tiles with the same members (by two sums of hashes and the count) give the same pairs: one of them is enough
    names = [F.sum(F.xxhash64(*c).cast("decimal(20,0)")).alias(f"s{i}") for i, c in enumerate((("id", "early"), ("early", "n", "id")))]
    mixed = rows.groupBy("token", "band").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.bool_or("home").alias("some"), F.count("*").alias("m"), *names).where("lo < hi and some")
    mixed = mixed.groupBy("band", "s0", "s1", "m").agg(F.min("token").alias("token")).select("token", "band", F.ceil(F.col("m") / TILE).cast("int").alias("k"))
    rows = rows.join(mixed, ["token", "band"]).withColumn("block", F.pmod(F.xxhash64("id"), F.col("k")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    tile = F.xxhash64("token", "band", F.least("block", "other"), F.greatest("block", "other"))
    rows = rows.join(_halved(owners), "id").select(tile.alias("tile"), (F.col("block") == F.col("other")).alias("inner"), "block", "home", "id", "n", "early", "label", "bitmap")
    parts = int(owners.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def tiles_of(batches):
        rest = None
        for b in batches:
            t = pa.Table.from_batches([b]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([b])])
            key = t.column("tile").to_numpy()
            cut = int(np.flatnonzero(key != key[-1])[-1] + 1) if (key != key[-1]).any() else 0
            rest = t.slice(cut)
            if cut:
                yield from _compare(t.slice(0, cut), percent)
        if rest is not None:
            yield from _compare(rest, percent)

    dealt = rows.repartition(parts, "tile").sortWithinPartitions("tile", "n", "id")
    return map_stream(dealt, tiles_of, "a long, b long").distinct()


def _compare(t: pa.Table, percent: int) -> Iterator[pa.RecordBatch]:
    """The pairs of whole tiles (rows of a tile stand together) that are still open and that sizes and bitmaps admit."""
    tile, ids, n, label, block = (t.column(c).to_numpy() for c in ("tile", "id", "n", "label", "block"))
    inner, early, home, maps = t.column("inner").to_numpy(), t.column("early").to_numpy(), t.column("home").to_numpy(), t.column("bitmap").to_pylist()
    size = np.array([len(x) for x in maps])
    flat = {}
    for d in range(1, len(ids)):
        a = np.flatnonzero((tile[:-d] == tile[d:]) & (100 * n[:-d] >= percent * n[d:]))  # sizes rise within a tile
        if not len(a):
            break
        b = a + d
        ok = (label[a] != label[b]) & (inner[a] | (block[a] != block[b])) & home[b] & early[a] & (early[b] | (n[a] < n[b]))
        a, b = a[ok], b[ok]
        least = np.minimum(size[a], size[b])
        for z in np.unique(least):
            if z not in flat:
                flat[z] = np.stack([_folded(x, z) if len(x) >= z else np.zeros(z, np.uint8) for x in maps])
            x, y = a[least == z], b[least == z]
            near = bound_passes(n[x], n[y], _POP[flat[z][x] ^ flat[z][y]].sum(1), percent)
            x, y = x[near], y[near]
            if len(x):
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(ids[x], ids[y])), pa.array(np.maximum(ids[x], ids[y]))], ["a", "b"])


def intersections(x: list[np.ndarray], y: list[np.ndarray], columns: int = 8192) -> np.ndarray:
    """Exact sizes of the intersections of all sets of x with all of y, as products of incidence matrices; only members that
    several sets hold get a column, and ``columns`` of them are taken at a time."""
    every = np.concatenate([*x, *y])
    row = np.repeat(np.arange(len(x) + len(y)), [len(s) for s in (*x, *y)])
    vocabulary, at, often = np.unique(every, return_inverse=True, return_counts=True)
    shared = np.flatnonzero(often > 1)
    place = np.full(len(vocabulary), -1)
    place[shared] = np.arange(len(shared))
    col = place[at]
    row, col = row[col >= 0], col[col >= 0]
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    out = np.zeros((len(x), len(y)), np.float64)
    for c in range(0, len(shared), columns):
        lo, hi = np.searchsorted(col, (c, c + columns))
        m = np.zeros((len(x) + len(y), min(columns, len(shared) - c)), np.float32)
        m[row[lo:hi], col[lo:hi] - c] = 1
        out += m[: len(x)] @ m[len(x) :].T
    return np.rint(out).astype(np.int64)


def _tile_links(ids: np.ndarray, block: np.ndarray, sets: list[np.ndarray], percent: int) -> np.ndarray:
    """The pairs (a, b), a < b, of a tile that reach the threshold: between its two blocks, or within its only one."""
    first = np.flatnonzero(block == block[0])
    rest = np.flatnonzero(block != block[0])
    if not len(rest):
        rest = first
    x, y = [sets[i] for i in first], [sets[i] for i in rest]
    common = intersections(x, y)
    total = np.array([len(s) for s in x])[:, None] + np.array([len(s) for s in y])[None, :]
    i, j = np.nonzero(100 * common >= percent * (total - common))
    a, b = ids[first[i]], ids[rest[j]]
    pairs = np.unique(np.column_stack([np.minimum(a, b), np.maximum(a, b)])[a != b], axis=0)
    return pairs


def _within_components(docs: DataFrame, group: DataFrame, width: int, percent: int, pairs: bool) -> DataFrame:
    """The links of all members (id, label) of the components: (id, n_links), or with ``pairs`` the links (a, b) themselves. Two
    linked classes are of one component, so a component is cut into blocks by hash, a tile meets two blocks, and every pair of
    sets is met in one tile. Exact intersections decide. A tile adds up its links and sends one row a member, not one a pair;
    a set is sent to as many tiles as its component has blocks."""
    blocks_of = group.groupBy("label").agg(F.ceil(F.count("*") / GROUP).cast("int").alias("k"))
    group = materialise(group.join(blocks_of, "label").select("id", "label", "k", F.pmod(F.xxhash64("id", F.lit(GROUP)), F.col("k")).cast("int").alias("block")), "groups")
    bits = membership_filter(group, "id")

    def sets(b: pa.RecordBatch):
        live = np.flatnonzero(passes(bits, b.column("slot").to_numpy()))
        if not len(live):
            return None
        b = b.take(pa.array(live))
        return pa.RecordBatch.from_arrays([b.column("id").cast(pa.int64()), pa.array([s.view(np.int64) for s in shingle_sets(b.column("text"), width)], pa.list_(pa.int64()))], ["id", "s"])

    have = map_batches(docs.where("id is not null").select("id", "text", may_contain("id").alias("slot")), sets, "id long, s array<long>").where(F.size("s") > 0)
    have = materialise(have.join(group.select("id"), "id", "left_semi").dropDuplicates(["id", "s"]), "sets")
    spread = group.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    spread = spread.select("id", "block", F.xxhash64("label", F.least("block", "other"), F.greatest("block", "other")).alias("tile"))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def decide(batches):
        held: list = []

        def found():
            ids, block = np.array([h[1] for h in held], np.int64), np.array([h[2] for h in held], np.int64)
            links = _tile_links(ids, block, [h[3] for h in held], percent)
            if not len(links):
                return
            if pairs:
                yield pa.RecordBatch.from_arrays([pa.array(links[:, 0]), pa.array(links[:, 1])], ["a", "b"])
            else:
                i, n = np.unique(links, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(n)], ["id", "n_links"])

        for t in batches:
            tile, ids, block, s = t.column("tile").to_numpy(), t.column("id").to_numpy(), t.column("block").to_numpy(), t.column("s")
            for k in range(t.num_rows):
                if held and held[0][0] != tile[k]:
                    yield from found()
                    held = []
                held.append((tile[k], ids[k], block[k], s[k].values.to_numpy().view(np.uint64).copy()))
        if held:
            yield from found()

    dealt = spread.join(have, "id").select("tile", "id", "block", "s").repartition(parts, "tile").sortWithinPartitions("tile", "block")
    out = map_stream(dealt, decide, "a long, b long" if pairs else "id long, n_links long")
    out = materialise(out if pairs else out.groupBy("id").agg(F.sum("n_links").alias("n_links")), "links")
    discard(group, have)
    return out


def _connecting(docs: DataFrame, owners: DataFrame, tiles: DataFrame, width: int, percent: int) -> DataFrame:
    """Verified pairs that connect each component: leaders and partners first, then the pairs that are still apart."""
    star = tiles.select("id", F.explode(F.array("leader", "partner")).alias("to")).where("to <> id")
    star = star.select(F.least("to", "id").alias("a"), F.greatest("to", "id").alias("b")).distinct()
    first = _verified(docs, owners, star, width, percent)
    labels = components(first)
    more = _verified(docs, owners, _cross_pairs(tiles, owners, labels, percent), width, percent)
    return first.union(more)


def jaccard_join(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, links: str = "pairs") -> tuple[DataFrame, DataFrame]:
    """Exact similarity join of whole texts on word n-grams.

    Returns (members, links). members: ``id, n_shingles, class_id, component_id, n_links``, a row for each input row, where
    class_id is the smallest id with an equal set and n_links counts the other classes whose sets reach the threshold with a
    row's class. What ``links`` asks for: with ``pairs`` the second table holds every such pair (a, b) of different class ids, a
    number that grows with the square of a group's size; with ``counts`` the links are counted without being written, and the
    table holds only pairs that connect each component; with ``components`` n_links counts these alone.

    Defined cases: a null or wordless text has no shingles, is linked with nothing and forms its own class and component;
    rows that share an id are one vertex; a row without id keeps its n_shingles and has null class and component; other
    columns of the input are ignored; an empty input gives empty results.
    """
    docs = documents.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    sketch = frequency_sketch(docs, width)
    sig = signatures(docs, sketch, width, percent)
    named = sig.where("n > 0 and id is not null")
    classes = materialise(named.groupBy("h1", "h2", "n").agg(F.min("id").alias("rep")), "classes")
    owners = named.join(classes.select("h1", "h2", "n", F.col("rep").alias("id")), ["h1", "h2", "n", "id"], "left_semi").dropDuplicates(["h1", "h2", "n", "id"])
    owners = materialise(owners.select("id", "n", "bitmap", "tokens", "early"), "owners")
    tiles = _shared_tokens(owners, sketch, percent)
    found = _connecting(docs, owners, tiles, width, percent)
    discard(tiles, owners)
    same = sig.join(classes, ["h1", "h2", "n"], "left").select("id", F.col("n").alias("n_shingles"), F.when(F.col("id").isNotNull(), F.coalesce("rep", "id")).alias("class_id"))
    # copies of one id in several classes tie those classes together
    least = same.where("id is not null").groupBy("id").agg(F.min("class_id").alias("a"), F.max("class_id").alias("most")).where("a < most")
    tie = same.join(least, "id").select("a", F.col("class_id").alias("b"))
    final = components(found.union(tie))
    if links == "components":
        degree = _degrees(found)
    else:
        counted = _within_components(docs, final, width, percent, links == "pairs")
        found, degree = (counted, _degrees(counted)) if links == "pairs" else (found, counted.withColumnRenamed("id", "class_id"))
    out = same.join(final.toDF("class_id", "label"), "class_id", "left").join(degree, "class_id", "left")
    return out.select("id", "n_shingles", "class_id", F.coalesce("label", "class_id").alias("component_id"), F.coalesce("n_links", F.lit(0)).alias("n_links")), found


def _degrees(links: DataFrame) -> DataFrame:
    return links.select(F.explode(F.array("a", "b")).alias("class_id")).groupBy("class_id").agg(F.count("*").alias("n_links"))
