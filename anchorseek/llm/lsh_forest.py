r"""Near-duplicate detection with an LSH forest.

Each text becomes its set of distinct word shingles and 192 min-wise hashes, cut into 24 trees of 8. A tree is
an order: its texts are sorted by their signatures (dealt over ranges, the id breaking ties, so that no range
is larger than others), and the longest common prefix of neighbours is read off in one pass over each range.
Neighbours that share a prefix of 4 or more are a region, the candidates of one another. Depth adapts to the
region. A region of at most `GROUP` texts (and `ROOM` shingles) is compared as it is. A larger one is cut
into groups of that size where its neighbours share the shortest prefix, so texts with the longest ones stay
together, and each group also gets the region's hub: a text of its longest run of equal signatures, and so
the likely original of a large family. Then, of each large region, the texts that are not yet connected with
its main component are compared with all of the region, block by block, so nothing rests on the cuts or on
the borders of the ranges: every pair with a common prefix of 4 in some tree is compared on its full sets,
unless both are already in one component.

A pair at the similarity s has no such prefix with the chance (1 - s^4)^24: 3.2e-6 at 0.80, 2.0e-8 at 0.85.

Texts with equal sets are one class throughout; groups hand on a star of each connected part, so links grow
with the texts, not with pairs. Components come from label propagation with pointer jumping over settled
tables. A bitmap that tells whose full sets are needed goes through the driver: 8 bits a candidate, at most
`MOST_BITS`; with more candidates the texts are joined with them instead.

Defined results: null or empty text, or text without words, has an empty set and is linked with nothing; a
text of fewer than `width` words has one shingle, the whole; rows with equal ids are one document; a row
with a null id is its own component, null, and kept; an empty table gives an empty result; ids that are not
integers are refused.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER_BYTES, discard, lean, parts_of, settled, table

WIDTH = 5
TREES = 24
#: Minima of a tree, and the common prefix that makes neighbours candidates.
DEPTH, PREFIX = 8, 4
#: Texts of a group, and shingles of all of them.
GROUP = 192
ROOM = 4_000_000
#: Bits of the marks of `without`, and the most of a bitmap of candidates.
BITS = 1 << 26
MOST_BITS = 1 << 28
LINK = (85, 100)
_GOLD, _MIX1, _MIX2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= 200_000:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * _MIX1
    h = (h ^ (h >> np.uint64(27))) * _MIX2
    return h ^ (h >> np.uint64(31))


def shingles(text: str | None, width: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct 64-bit shingle hashes of a text."""
    words = (text or "").encode().translate(LOWER_BYTES).split()
    if not words:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    n = max(1, len(w) - width + 1)
    h = np.full(n, min(len(w), width), np.uint64)
    for i in range(min(len(w), width)):
        h *= _GOLD
        h += w[i : n + i]
    h = np.sort(_mixed(h))  # numpy's unique goes through a hash table, which is slower
    first = np.ones(len(h), bool)
    np.not_equal(h[1:], h[:-1], out=first[1:])
    return h[first]


def _seeds(count: int) -> tuple[np.ndarray, np.ndarray]:
    base = _mixed(np.arange(1, 2 * count + 1, dtype=np.uint64) * _GOLD).astype(np.uint32)
    return base[:count, None], base[count:, None] | np.uint32(1)


def signature(s: np.ndarray, seeds) -> np.ndarray:
    """Min-wise hashes of a shingle set."""
    flip, odd = seeds
    low = (s >> np.uint64(32)).astype(np.uint32)
    out = np.full(len(flip), 0xFFFFFFFF, np.uint32)
    for at in range(0, len(low), 2048):
        v = (low[None, at : at + 2048] ^ flip) * odd
        v ^= v >> np.uint32(15)
        v *= np.uint32(0x846CA68B)
        v ^= v >> np.uint32(16)
        np.minimum(out, v.min(1), out=out)
    return out


def tree_keys(sig: np.ndarray, trees: int) -> np.ndarray:
    """Sort keys of every tree: a hash of its first PREFIX minima, and 16 bits of each prefix beyond."""
    per = sig.reshape(trees, -1).astype(np.uint64)
    h = np.arange(1, trees + 1, dtype=np.uint64) * _GOLD
    for i in range(PREFIX):
        h = _mixed(h * _GOLD + per[:, i])
    deep, rest = h, np.zeros(trees, np.uint64)
    for i in range(PREFIX, per.shape[1]):
        deep = _mixed(deep * _GOLD + per[:, i])
        rest = (rest << np.uint64(16)) | (deep >> np.uint64(48))
    return np.stack([h, rest], axis=1)


def common_prefix(near: np.ndarray, deep: np.ndarray) -> np.ndarray:
    """Longest common prefix of every row with the one before it; 0 where it is below PREFIX."""
    out = np.zeros(len(near), np.int8)
    if len(near) > 1:
        x = deep[1:] ^ deep[:-1]
        levels = DEPTH - PREFIX
        beyond = sum(((x >> np.uint64(16 * (levels - 1 - i))) == 0).astype(np.int8) for i in range(levels))
        out[1:] = np.where(near[1:] == near[:-1], PREFIX + beyond, 0)
    return out


def _sketcher(width: int, trees: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, seeds = WordHashes(), _seeds(trees * DEPTH)
        for batch in batches:
            for part in range(0, batch.num_rows, 1000):
                rows = batch.slice(part, 1000)
                sizes, sums, keys = [], [], []
                for t in rows.column("_t"):
                    s = shingles(t.as_py(), width, hashes)
                    sizes.append(len(s))
                    sums.append((s.sum(dtype=np.uint64), _mixed(s).sum(dtype=np.uint64)))
                    keys.append(tree_keys(signature(s, seeds), trees).ravel())
                flat = np.concatenate(keys).view(np.int64)
                both = np.array(sums, np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays(
                    [rows.column("_id"), pa.array(sizes, pa.int64()), pa.array(both[:, 0]), pa.array(both[:, 1]), pa.ListArray.from_arrays(pa.array(np.arange(len(sizes) + 1) * 2 * trees, pa.int32()), pa.array(flat))],
                    names=["_id", "_n", "_h1", "_h2", "_keys"],
                )

    return lean(run)


def cuts_of(prefix: np.ndarray, weight: np.ndarray, group: int, room: int) -> list[int]:
    """Places where a region's rows are cut into groups of at most `group` rows and, if they have two, about
    `room` shingles: in the second half of what fits, where neighbours share the shortest prefix, the last of those."""
    out, at, n = [0], 0, len(prefix)
    total = np.concatenate([[0], np.cumsum(weight)])
    while True:
        fits = min(group, max(2, int(np.searchsorted(total, total[at] + room, side="right")) - 1 - at))
        if at + fits >= n:
            return out
        low = at + max(1, fits // 2)
        window = prefix[low : at + fits + 1][::-1]
        at = at + fits - int(window.argmin())
        out.append(at)


def _neighbours(group: int, room: int):
    """Rows in the order of their trees -> (_region, _cut, _rep, _n, _same): rows that share a prefix of PREFIX
    with a neighbour, or stand at an end of the range, the group of each, and the length of its run of equal keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def closed(rows: list[tuple], first: bool, last: bool):
            near, deep, rep, weight = (np.concatenate(c) for c in zip(*rows))
            prefix = common_prefix(near, deep)
            opens = prefix == 0
            starts = np.flatnonzero(opens)
            sizes = np.diff(np.append(starts, len(near)))
            cut = opens.copy()
            weights = np.add.reduceat(weight, starts)
            for s, n in zip(starts[(sizes > group) | (weights > room)], sizes[(sizes > group) | (weights > room)]):
                cut[s + np.array(cuts_of(prefix[s : s + n], weight[s : s + n], group, room))] = True
            number = np.cumsum(cut) - 1
            group_id = _mixed(near ^ _mixed(rep[cut].view(np.uint64))[number])
            runs = np.cumsum(prefix < DEPTH) - 1
            same = np.bincount(runs)[runs]
            wanted = np.repeat(sizes > 1, sizes)
            if first:
                wanted[: sizes[0]] = True
            if last:
                wanted[len(wanted) - sizes[-1] :] = True
            at = np.flatnonzero(wanted)
            return pa.RecordBatch.from_arrays(
                [pa.array(near[at].view(np.int64)), pa.array(group_id[at].view(np.int64)), pa.array(rep[at]), pa.array(weight[at]), pa.array(same[at].astype(np.int64))],
                names=["_region", "_cut", "_rep", "_n", "_same"],
            )

        first = True
        for batch in batches:
            if not batch.num_rows:
                continue
            near, deep, rep, weight = (batch.column(c).to_numpy() for c in ("_near", "_deep", "_rep", "_n"))
            rows = (near.view(np.uint64), deep.view(np.uint64), rep, weight)
            turns = np.flatnonzero(rows[0][1:] != rows[0][:-1]) + 1
            same_run = not held or held[-1][0][-1] == rows[0][0]
            if not len(turns) and same_run:
                held.append(rows)
                continue
            # all but the last run is whole: it ends in this batch
            last = int(turns[-1]) if len(turns) else 0
            done = held + ([tuple(c[:last] for c in rows)] if last else [])
            yield closed(done, first, False)
            first, held = False, [tuple(c[last:] for c in rows)]
        if held:
            yield closed(held, first, True)

    return lean(run)


def _bit_of(ids: np.ndarray, bits: int) -> np.ndarray:
    return (_mixed(ids.astype(np.int64).view(np.uint64)) & np.uint64(bits - 1)).astype(np.int64)


def _wanted(candidates: DataFrame, column: str, bits: int) -> np.ndarray:
    """A bitmap over the hashed ids, put together on the executors."""

    def mark(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(_bit_of(batch.column(0).to_numpy(), bits))], names=["bit"])

    places = candidates.select(F.col(column).cast("long")).mapInArrow(lean(mark), "bit bigint")
    pages = places.groupBy(F.shiftright("bit", 15).alias("page")).agg(F.bitmap_construct_agg(F.col("bit").bitwiseAND(32767)).alias("b"))
    out = np.zeros((bits >> 15, 4096), np.uint8)
    for page, b in pages.toLocalIterator():
        out[page] = np.frombuffer(b, np.uint8)
    return out.ravel()


def _set_maker(width: int, wanted: np.ndarray | None):
    """Shingle sets of the documents whose bit is set; of all without a bitmap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            rows = np.arange(batch.num_rows)
            if wanted is not None:
                at = _bit_of(batch.column("_id").to_numpy(), len(wanted) * 8)
                rows = np.flatnonzero((wanted[at >> 3] >> (at & 7).astype(np.uint8)) & 1)
            batch = batch.take(pa.array(rows))
            for part in parts_of(batch, "_t", 500):
                sets = [shingles(t.as_py(), width, hashes) for t in part.column("_t")]
                offsets = np.concatenate([[0], np.cumsum([len(s) for s in sets])])
                yield pa.RecordBatch.from_arrays([part.column("_id"), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate(sets).view(np.int64)))], names=["_rep", "_set"])

    return lean(run)


def linked_parts(sets: list[np.ndarray], link=LINK) -> np.ndarray:
    """For every set, the number of the first set of its connected part; all pairs are judged on full sets."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets], np.int64)
    if n == 2:
        shared = np.array([[0, len(np.intersect1d(sets[0], sets[1], assume_unique=True))]] * 2)
        shared[1, 0] = shared[0, 1]
    else:
        values = np.concatenate(sets)
        owner = np.repeat(np.arange(n), sizes)
        order = np.argsort(values, kind="stable")
        values, owner = values[order], owner[order]
        fresh = np.concatenate([[True], values[1:] != values[:-1]]) if len(values) else np.empty(0, bool)
        number = np.cumsum(fresh) - 1
        often = np.bincount(number)[number] >= 2 if len(values) else np.empty(0, bool)
        owner, number = owner[often], number[often]
        shared = np.zeros((n, n), np.float32)
        if len(number):
            number = np.cumsum(np.concatenate([[0], number[1:] != number[:-1]]))
            for first in range(0, int(number[-1]) + 1, 8192):
                lo, hi = np.searchsorted(number, [first, first + 8192])
                grid = np.zeros((n, 8192), np.float32)
                grid[owner[lo:hi], number[lo:hi] - first] = 1
                shared += grid @ grid.T
        shared = shared.astype(np.int64)
    linked = link[1] * shared >= link[0] * (sizes[:, None] + sizes[None, :] - shared)
    linked &= shared > 0
    part = np.full(n, -1)
    for i in range(n):
        if part[i] < 0:
            part[i], edge = i, [i]
            while len(edge):
                edge = np.flatnonzero(linked[edge].any(0) & (part < 0))
                part[edge] = i
    return part


def _verifier(link):
    """Rows sorted by group; a star of every connected part goes out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, ids, sets = None, [], []
        out_a, out_b = [], []

        def close():
            if len(ids) > 1:
                order = np.argsort(ids, kind="stable")
                part = linked_parts([sets[i] for i in order], link)
                sorted_ids = [ids[i] for i in order]
                for i, p in enumerate(part):
                    if p != i and sorted_ids[p] != sorted_ids[i]:
                        out_a.append(sorted_ids[p])
                        out_b.append(sorted_ids[i])

        for batch in batches:
            gids, reps = batch.column("_gid").to_numpy(), batch.column("_rep").to_pylist()
            column = batch.column("_set")
            offsets, values = column.offsets.to_numpy(), column.values.to_numpy()
            for i in range(batch.num_rows):
                if gids[i] != group:
                    close()
                    group, ids, sets = gids[i], [], []
                ids.append(reps[i])
                sets.append(values[offsets[i] : offsets[i + 1]].copy())
            if out_a:
                yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["_a", "_b"])
                out_a, out_b = [], []
        close()
        if out_a:
            yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["_a", "_b"])

    return lean(run)


def _links(groups: DataFrame, texts: DataFrame, width: int, link) -> DataFrame:
    """(_a, _b) from groups (_gid, _rep) after comparing the full sets inside each."""
    spark = groups.sparkSession
    candidates = groups.select("_rep").distinct().count()
    if 8 * candidates <= MOST_BITS:
        bits = max(1 << 20, 1 << (8 * candidates - 1).bit_length())
        sets = texts.mapInArrow(_set_maker(width, _wanted(groups, "_rep", bits)), "_rep bigint, _set array<bigint>")
    else:
        some = texts.join(groups.select(F.col("_rep").alias("_id")).distinct().hint("merge"), "_id", "left_semi")
        sets = some.mapInArrow(_set_maker(width, None), "_rep bigint, _set array<bigint>")
    # both sides grow with the corpus: never a broadcast, so that costs grow evenly
    placed = groups.hint("merge").join(sets, "_rep").select("_gid", "_rep", "_set")
    found = placed.repartition("_gid").sortWithinPartitions("_gid").mapInArrow(_verifier(link), "_a bigint, _b bigint")
    return settled(found.distinct(), "links") if candidates else spark.createDataFrame([], "_a bigint, _b bigint")


def components(links: DataFrame) -> DataFrame:
    """(_node, _label) of every end of a link; the label is the smallest node that can be reached."""
    both = settled(links.union(links.select("_b", "_a")).toDF("_node", "_other").where("_node != _other").distinct(), "links-both")
    labels = settled(both.groupBy("_node").agg(F.least(F.col("_node"), F.min("_other")).alias("_label")), "labels")
    while True:
        near = both.join(labels.toDF("_other", "_l"), "_other").groupBy("_node").agg(F.min("_l").alias("_near"))
        step = settled(labels.join(near, "_node").select("_node", F.least("_label", "_near").alias("_label"), (F.col("_near") < F.col("_label")).alias("_moved")), "labels-step")
        jumped = step.select("_node", "_label", "_moved").join(step.select(F.col("_node").alias("_label"), F.col("_label").alias("_far")), "_label", "left")
        former, labels = labels, settled(jumped.select("_node", F.least("_label", F.coalesce("_far", "_label")).alias("_label")), "labels")
        moved = step.where("_moved").limit(1).count()
        discard(former, step)
        if not moved:
            discard(both)
            return labels


def _large(room: int):
    return (F.col("_size") > GROUP) | (F.col("_weight") > room)


def _groups(members: DataFrame, room: int) -> DataFrame:
    """(_gid, _rep): small regions as they are, large ones as they are cut, with their hubs."""
    small = members.where(~_large(room)).select(F.col("_region").alias("_gid"), "_rep")
    large = members.where(_large(room))
    hubs = large.groupBy("_region").agg(F.max(F.struct("_same", -F.col("_rep"))).alias("_h")).select("_region", (-F.col("_h.col2")).alias("_hub"))
    with_hubs = large.select("_region", "_cut").distinct().join(hubs, "_region").select(F.col("_cut").alias("_gid"), F.col("_hub").alias("_rep"))
    return small.union(large.select("_cut", "_rep")).union(with_hubs).distinct()


def _rest(members: DataFrame, labels: DataFrame, room: int) -> DataFrame | None:
    """(_gid, _rep): blocks that compare a large region's unconnected texts with all of the region."""
    large = members.where(_large(room)).select("_region", "_rep", "_size", "_weight")
    if large.limit(1).count() == 0:
        return None
    found = settled(large.join(labels.withColumnRenamed("_node", "_rep"), "_rep", "left").withColumn("_label", F.coalesce("_label", "_rep")), "region-components")
    counts = found.groupBy("_region", "_label").agg(F.count(F.lit(1)).alias("_c"))
    main = counts.groupBy("_region").agg(F.max(F.struct("_c", "_label")).alias("_m"), F.sum("_c").alias("_all"))
    main = main.select("_region", F.col("_m._label").alias("_main"), (F.col("_all") - F.col("_m._c")).alias("_left")).where("_left > 0")
    if main.limit(1).count() == 0:
        return None
    # texts of a block: fewer where they are long
    unit = F.least(F.lit(GROUP), F.greatest(F.lit(1), F.floor(F.col("_size") * room / F.col("_weight"))))
    blocks_all, blocks_left = F.ceil(F.col("_size") / unit).cast("int"), F.ceil(F.col("_left") / unit).cast("int")
    rows = found.join(main, "_region")
    place = F.xxhash64("_rep", "_region")
    as_any = rows.select("_region", "_rep", F.pmod(place, blocks_all).alias("_j"), F.explode(F.sequence(F.lit(0), blocks_left - 1)).alias("_i"))
    as_left = rows.where("_label != _main").select("_region", "_rep", F.explode(F.sequence(F.lit(0), blocks_all - 1)).alias("_j"), F.pmod(place, blocks_left).alias("_i"))
    gid = F.xxhash64("_region", F.col("_i").cast("int"), F.col("_j").cast("int")).alias("_gid")
    return settled(as_any.select(gid, "_rep").union(as_left.select(gid, "_rep")).distinct(), "rest-blocks")


def without(docs: DataFrame, dropped: DataFrame, doc_id="doc_id") -> DataFrame:
    """docs but for those whose id is in `dropped` (doc_id). Texts move only where a hash of their id is marked.

    The marks are a bitmap of BITS bits in pages, 8 MB however large the corpus; what they cannot rule out is
    joined exactly.
    """
    bit = lambda c: F.xxhash64(F.coalesce(c.cast("long"), F.lit(-1).cast("long"))).bitwiseAND(F.lit(BITS - 1).cast("long"))
    ids = dropped.select(F.col(doc_id).cast("long").alias("_gone")).where("_gone IS NOT NULL")
    place = bit(F.col("_gone"))
    marks = settled(ids.groupBy(F.shiftright(place, 15).alias("_page")).agg(F.bitmap_construct_agg(place.bitwiseAND(32767)).alias("_bits")), "dropped-marks")
    packed = docs.select(F.struct(*docs.columns).alias("_row"), F.col(doc_id).cast("long").alias("_own"))
    own = bit(F.col("_own"))
    offset = own.bitwiseAND(32767)
    byte = F.conv(F.hex(F.substring("_bits", F.shiftright(offset, 3).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    marked = F.coalesce(F.call_function("getbit", byte, offset.bitwiseAND(7).cast("int")) == 1, F.lit(False))
    seen = packed.join(F.broadcast(marks), F.shiftright(own, 15) == F.col("_page"), "left")
    kept = seen.where(~marked).select("_row").union(seen.where(marked).select("_row", "_own").join(ids.hint("merge"), F.col("_own") == F.col("_gone"), "left_anti").select("_row"))
    return kept.select(*[F.col(f"_row.`{c}`").alias(c) for c in docs.columns])


def near_duplicates(docs: DataFrame, doc_id="doc_id", text="text", width=WIDTH, link=LINK, room=ROOM) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept), one row a row of docs. doc_id is an integer column.

    link: (p, q) links sets with q * intersection >= p * union.
    """
    if docs.schema[doc_id].dataType.simpleString() not in ("bigint", "int", "smallint", "tinyint"):
        raise TypeError(f"{doc_id} is not an integer column")
    everything = docs.select(F.col(doc_id).cast("long").alias("_id"), F.col(text).alias("_t"))
    texts = everything.where(F.col("_id").isNotNull())
    sketches = settled(everything.mapInArrow(_sketcher(width, TREES), "_id bigint, _n bigint, _h1 bigint, _h2 bigint, _keys array<bigint>"), "sketches")
    valid = sketches.where("_id IS NOT NULL AND _n > 0")
    classes = settled(valid.groupBy("_n", "_h1", "_h2").agg(F.min_by("_keys", "_id").alias("_keys"), F.min("_id").alias("_id")), "classes")
    trees = F.transform(F.sequence(F.lit(0), F.lit(TREES - 1)), lambda i: F.struct(i.alias("_tree"), F.get("_keys", 2 * i).alias("_near"), F.get("_keys", 2 * i + 1).alias("_deep")))
    rows = classes.select(F.col("_id").alias("_rep"), "_n", F.explode(trees).alias("_k")).select("_k.*", "_rep", "_n")
    order = ["_tree", "_near", "_deep", "_rep"]
    seen = settled(rows.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_neighbours(GROUP, room), "_region bigint, _cut bigint, _rep bigint, _n bigint, _same bigint"), "neighbours")
    regions = seen.groupBy("_region").agg(F.count(F.lit(1)).alias("_size"), F.sum("_n").alias("_weight"), F.bit_xor(F.xxhash64("_rep")).alias("_who")).where("_size > 1")
    # regions with the same texts, in whatever tree, are compared once
    regions = regions.groupBy("_size", "_weight", "_who").agg(F.min("_region").alias("_region")).drop("_who")
    members = settled(seen.join(regions, "_region"), "members")
    discard(seen)
    groups = settled(_groups(members, room), "groups")
    links = _links(groups, texts, width, link)
    labels = components(links)
    rest = _rest(members, labels, room)
    if rest is not None:
        more = _links(rest, texts, width, link)
        labels = components(more.union(links).distinct())
        discard(rest, more)
    discard(members, groups, links)
    same = classes.select("_n", "_h1", "_h2", F.col("_id").alias("_rep"))
    # a repeated id is one document: its rows share the smallest label
    out = (
        sketches.drop("_keys")
        .join(same, ["_n", "_h1", "_h2"], "left")
        .join(labels.withColumnRenamed("_node", "_rep"), "_rep", "left")
        .withColumn("component_id", F.when(F.col("_n") > 0, F.coalesce("_label", "_rep", "_id")).otherwise(F.col("_id")))
    )
    return out.select(F.col("_id").alias("doc_id"), F.col("_n").alias("n_shingles"), "component_id", F.coalesce(F.col("_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def op3_near_duplicates(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), link=(85, 100))


OP3_SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT *, unnest(range(1, greatest(len(w) - 5, 0) + 2)) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
shared AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM shared JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 85 * (x.n + y.n - i)),
reach AS (WITH RECURSIVE r(a, b) AS (SELECT doc_id, doc_id FROM w UNION SELECT r.a, links.b FROM r JOIN links ON r.b = links.a) SELECT a, min(b) AS c FROM r GROUP BY a)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, c AS component_id, w.doc_id = c AS kept
FROM w LEFT JOIN n USING (doc_id) JOIN reach ON reach.a = w.doc_id
"""
