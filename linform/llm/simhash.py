"""Near duplicates by SimHash, compared in bit-sliced form.

Fingerprints are 64-bit. Equal ones are merged first. Two fingerprints within the radius agree on some choice
of bit blocks (with b blocks and radius r, on b - r of them), so each is dealt to one bucket for each choice;
the number of blocks grows with the number of fingerprints, which keeps buckets of unrelated ones small and
loses no pair at any size. In a bucket the fingerprints are stored as bit planes (one bit of 64 fingerprints
in a word). One pass compares every lane with the lane s places on: the planes are XORed with their shifted
selves and the differences added by carry-save counters with a sticky overflow; a block is abandoned as soon as
every lane is beyond the radius. Passes s = 1, 2, ... cover all pairs of a bucket. Buckets of more than
BLOCK fingerprints are cut in blocks, and pairs of blocks are compared as tasks of their own, so no task holds
an unbounded bucket. Of the links in a bucket only a spanning forest leaves the task; components follow from
it in contractions over tables in the shared folder.

Similarity (similar_groups) is another question: sets of shingles with a Jaccard similarity of 0.8 lie some ten bits
apart and at times twenty, where agreeing bit blocks are of three or four bits and part nothing. There buckets
come from bands of least hashes of the shingles (a pair of similarity 0.8 shares none of them once in 20,000), the bit
planes of the sets only sort out pairs beyond a wide radius, and each link is checked on the whole sets. The SimHash
fingerprints of the sets are linked first, at the radius and by the buckets above; bands are for the similar pairs beyond it.

Null texts count as empty: fingerprint zero. A null doc_id takes part, but names no component unless all of
its members are null. Repeated rows are kept. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations, groupby, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.llm.common import arrow_map, connected_components, materialise, redealt, texts_of

BITS, SEED = 64, 42
#: Members of a bucket that one task compares; lanes of one block of planes; shingles hashed at a time.
BLOCK, LANES, CHUNK = 16_384, 65_536, 65_536
#: Bands of least hashes and hashes in each; radius beyond which no pair is of similarity 0.8 (mean 10 to 12 bits, deviation
#: 3); members of a bucket of whole sets that one task compares.
BANDS, IN_BAND, WIDE, SETS = 25, 5, 28, 1_024
_MIX = np.random.default_rng(SEED).integers(0, 1 << 63, (2, BANDS * IN_BAND), dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_hashes(text: str, shingle: int) -> Iterator[np.ndarray]:
    """Hashes of the word shingles, in order, a chunk at a time; texts of fewer words are one shingle."""
    words = text.encode("utf-8", "surrogatepass").lower().split()  # on bytes: A-Z and ASCII white space only
    for at in range(0, max(1, len(words) - shingle + 1) if words else 0, CHUNK):
        part = words[at : at + CHUNK + shingle - 1]
        runs = zip(*(part[k:] for k in range(shingle)), strict=False) if len(words) >= shingle else [part]
        yield np.fromiter(map(xxhash.xxh64_intdigest, map(b" ".join, runs), repeat(SEED)), np.uint64)


def majority(parts: Iterator[np.ndarray]) -> int:
    """The bits that over half of the hashes have."""
    ones, n = np.zeros(BITS, np.int64), 0
    for hashes in parts:
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        n += len(hashes)
    return int(np.packbits(2 * ones > n, bitorder="little").view(np.uint64)[0])


def fingerprint(text: str, shingle: int = 3) -> int:
    """SimHash of word shingles: a bit is set where over half of the shingles' hashes have it."""
    return majority(shingle_hashes(text, shingle))


def shingle_set(text: str, shingle: int) -> np.ndarray:
    """Distinct hashes of the word shingles, sorted."""
    parts = list(shingle_hashes(text, shingle))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def band_keys(held: np.ndarray) -> np.ndarray:
    """A hash of each band of least hashes of a set that is not empty."""
    least = np.empty(BANDS * IN_BAND, np.uint64)
    for at in range(0, len(least), IN_BAND):
        flip, factor = _MIX[:, at : at + IN_BAND, None]
        least[at : at + IN_BAND] = ((held ^ flip) * factor).min(axis=1)
    return np.array([xxhash.xxh64_intdigest(x.tobytes(), band) for band, x in enumerate(least.reshape(BANDS, IN_BAND))], np.uint64)


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two sorted sets."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """(doc_id, fp) for every row; fp is the fingerprint as a signed long."""

    def run(batch: pa.RecordBatch) -> dict:
        made = np.array([fingerprint(x, shingle) for x in texts_of(batch.column(1))], np.uint64)
        return {"doc_id": batch.column(0), "fp": pa.array(made.view(np.int64))}

    return arrow_map(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), run, "doc_id long, fp long")


def bit_planes(values: np.ndarray) -> np.ndarray:
    """uint64 values -> (64, words): plane k holds bit k of every value, 64 lanes a word, one spare word."""
    lanes = -(-len(values) // 64) * 64
    bits = np.zeros((lanes + 64, BITS), np.uint8)
    bits[: len(values)] = np.unpackbits(values.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.ascontiguousarray(np.packbits(bits.T, axis=1, bitorder="little")).view(np.uint64)


def _shifted(planes: np.ndarray, by: int, words: int) -> np.ndarray:
    """Lane i takes the value of lane i + by."""
    skip, bits = divmod(by, 64)
    part = planes[:, skip : skip + words + 1]
    if part.shape[1] < words + 1:
        part = np.pad(part, ((0, 0), (0, words + 1 - part.shape[1])))
    if not bits:
        return part[:, :words]
    return part[:, :words] >> np.uint64(bits) | part[:, 1:] << np.uint64(64 - bits)


def lanes_within(planes: np.ndarray, by: int, asked: np.ndarray, radius: int) -> np.ndarray:
    """Of the lanes asked (packed), those within radius bits of the lane `by` places on (packed)."""
    words = len(asked)
    counter = [np.zeros(words, np.uint64) for _ in range(radius.bit_length())]
    beyond = ~asked
    for k in range(0, BITS, 8):
        differ = planes[k : k + 8, :words] ^ _shifted(planes[k : k + 8], by, words)
        for carry in differ:
            for i, digit in enumerate(counter):
                counter[i], carry = digit ^ carry, digit & carry
            beyond |= carry
        if radius + 1 & radius:  # the counters hold more than the radius
            above, equal = np.zeros(words, np.uint64), np.full(words, ~np.uint64(0))
            for i in reversed(range(len(counter))):
                if radius >> i & 1:
                    equal &= counter[i]
                else:
                    above |= equal & counter[i]
                    equal &= ~counter[i]
            beyond |= above
        if (beyond == ~np.uint64(0)).all():
            break
    return ~beyond


def links_in_groups(values: np.ndarray, group: np.ndarray, radius: int, sure: Callable[[int, int], bool] | None = None, known: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Indices of pairs that form a spanning forest of the links inside groups. group: sorted numbers.

    sure: if given, pairs within the radius are links only where it says so. known: numbers of components that values of
    one group are in already; links inside them aren't asked for. Only pairs that do not hang together yet are compared;
    a group that is one component is done, and where nearly all of a large group is one, the few others are compared
    with all of it one by one.
    """
    root = np.arange(len(values))
    if known is not None and len(values):
        _, first, back = np.unique(np.stack([group, known]), axis=1, return_index=True, return_inverse=True)
        root = first[back.ravel()]

    def find(x: int) -> int:
        while (up := int(root[x])) != x:
            root[x] = root[up]
            x = int(root[x])
        return x

    def roots(at: np.ndarray) -> np.ndarray:
        found = root[at]
        while ((up := root[found]) != found).any():
            found = up
        return found

    def link(a: int, b: int) -> bool:
        ra, rb = find(a), find(b)
        if ra == rb or not (sure is None or sure(a, b)):
            return False
        root[ra] = rb
        out.append((a, b))
        return True

    def unsettled(lanes: np.ndarray, own: np.ndarray, label: np.ndarray, by: int) -> np.ndarray:
        """Which lanes are of groups that have pairs `by` or more places apart to compare."""
        starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
        ends = np.r_[starts[1:], len(own)]
        more = (np.minimum.reduceat(label, starts) != np.maximum.reduceat(label, starts)) & (ends - starts > by)
        for g in np.flatnonzero(more & (ends - starts >= 256)):
            place = slice(starts[g], ends[g])
            names, counts = np.unique(label[place], return_counts=True)
            others = np.flatnonzero(label[place] != names[counts.argmax()])
            if len(others) * 8 <= ends[g] - starts[g]:
                members = lanes[place]
                for o in others:
                    for i in np.flatnonzero(np.bitwise_count(values[members] ^ values[members[o]]) <= radius):
                        link(int(members[o]), int(members[i]))
                more[g] = False
        return np.repeat(more, ends - starts)

    out: list[tuple[int, int]] = []
    size = np.bincount(group)[group] if len(group) else np.zeros(0, int)
    order = np.lexsort((group, size))  # groups of a size together, so that passes end together
    order = order[size[order] > 1]
    at = 0
    while at < len(order):
        end = min(at + LANES, len(order))
        while end < len(order) and group[order[end]] == group[order[end - 1]]:
            end += 1
        lanes = order[at:end]
        at, by = end, 1
        planes, own, label = bit_planes(values[lanes]), group[lanes], roots(lanes)
        while len(lanes) > by:
            if by & by - 1 == 0:  # at passes 1, 2, 4, ...: leave out the groups that are done
                keep = unsettled(lanes, own, label, by)
                if not keep.any():
                    break
                if keep.sum() < 0.75 * len(lanes):
                    lanes = lanes[keep]
                    planes, own = bit_planes(values[lanes]), group[lanes]
                label = roots(lanes)
            same = own[by:] == own[:-by]
            if not same.any():
                break
            same &= label[by:] != label[:-by]
            if same.any():
                packed = np.packbits(np.pad(same, (0, -len(same) % 64)), bitorder="little").view(np.uint64)
                near = lanes_within(planes, by, packed, radius)
                if near.any() and sum([link(int(lanes[i]), int(lanes[i + by])) for i in np.flatnonzero(np.unpackbits(near.view(np.uint8), bitorder="little"))]):
                    label = roots(lanes)
            by += 1
    return out


def block_masks(count: int, radius: int, target: int = 64) -> list[int]:
    """Masks of the bits on which a pair must agree, one for each choice of blocks.

    The number of blocks is the least for which buckets of unrelated fingerprints stay near the target.
    """
    blocks = radius + 1
    while blocks < 16 and count > target << BITS * (blocks - radius) // blocks:
        blocks += 1
    edges = [BITS * i // blocks for i in range(blocks + 1)]
    part = [(1 << edges[i + 1]) - (1 << edges[i]) for i in range(blocks)]
    return [sum(part[i] for i in chosen) for chosen in combinations(range(blocks), blocks - radius)]


def fingerprint_links(distinct: DataFrame, radius: int = 3, block: int = BLOCK) -> DataFrame:
    """(fp) without repeats -> (a, b): links that connect all fingerprints within the radius of each other."""
    signed = [m - (1 << 64) if m >> 63 else m for m in block_masks(distinct.count(), radius)]
    choices = F.array(*(F.struct(F.lit(i).alias("choice"), F.col("fp").bitwiseAND(F.lit(m).cast("long")).alias("part")) for i, m in enumerate(signed)))
    dealt = distinct.select("fp", F.inline(choices))
    large = dealt.groupBy("choice", "part").agg(F.count("*").alias("n")).where(F.col("n") > block)
    cut = large.select("choice", "part", F.ceil(F.col("n") / (block / 2)).cast("int").alias("cuts"))
    placed = dealt.join(cut, ["choice", "part"], "left").withColumn("cuts", F.coalesce("cuts", F.lit(1)))
    own = F.pmod(F.xxhash64("fp"), F.col("cuts")).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.col("cuts") - 1))
    spread = placed.withColumn("own", own).select("fp", "choice", "part", "own", other.alias("other"))
    keys = [F.col("choice"), F.col("part"), F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j")]
    tasks = spread.select(*keys, "fp").repartition("choice", "part", "i", "j").sortWithinPartitions("choice", "part", "i", "j")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        for batch in batches:
            held.append(np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns]))
            last = held[-1][:4]
            if (last[:, :1] == last[:, -1:]).all() and len(held) > 1 and (held[-2][:4, -1] == last[:, 0]).all():
                continue  # all of one bucket, begun before
            rows = np.concatenate(held, axis=1)
            open_from = len(rows[0]) - int(np.argmax((rows[:4, ::-1] != rows[:4, -1:]).any(axis=0))) if (rows[:4] != rows[:4, -1:]).any() else 0
            if open_from:
                yield from told(rows[:, :open_from])
            held = [rows[:, open_from:]]
        if held:
            yield from told(np.concatenate(held, axis=1))

    def told(rows: np.ndarray) -> Iterator[pa.RecordBatch]:
        new = (rows[:4, 1:] != rows[:4, :-1]).any(axis=0)
        group = np.concatenate([[0], np.cumsum(new)]).astype(np.int64) if rows.shape[1] else np.zeros(0, np.int64)
        pairs = links_in_groups(np.ascontiguousarray(rows[4]).view(np.uint64), group, radius)
        if pairs:
            at = np.array(pairs).T
            yield pa.RecordBatch.from_arrays([pa.array(rows[4][at[0]]), pa.array(rows[4][at[1]])], names=["a", "b"])

    return tasks.mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 3) -> DataFrame:
    """(doc_id, fingerprint, component_id), one row for each row of docs."""
    each = materialise(fingerprints(docs, id_col, text_col, shingle), "simhash")
    distinct = materialise(each.groupBy("fp").agg(F.min("doc_id").alias("least")), "simhash-distinct")
    members = connected_components(fingerprint_links(distinct.select("fp"), radius))
    rooted = distinct.join(members, F.col("fp") == F.col("node"), "left").withColumn("root", F.coalesce("root", "fp"))
    least = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = rooted.join(redealt(least, "root"), "root").select("fp", "component_id")
    return each.join(named, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def sure_links(pairs: DataFrame, sets: DataFrame, similar: float) -> DataFrame:
    """Of pairs (a, b) of rows, those whose sets (row, held) are similar enough."""
    with_a = pairs.join(sets.select(F.col("row").alias("a"), F.col("held").alias("held_a")), "a")
    both = redealt(with_a, "b").join(sets.select(F.col("row").alias("b"), F.col("held").alias("held_b")), "b").select("a", "b", "held_a", "held_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            told = [jaccard(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)) >= similar for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            yield batch.select([0, 1]).filter(pa.array(told, pa.bool_()))

    return both.mapInArrow(run, "a long, b long")


def similar_links(sets: DataFrame, buckets: DataFrame, similar: float, block: int = SETS) -> DataFrame:
    """(row, fp, held), (row, key, root) -> (a, b): links that connect all rows of a bucket whose sets are similar
    enough and that have not one root.

    Buckets are cut in blocks: rows of a root that is common in the bucket in blocks of their own, the others by their
    root. Two blocks of one root are not compared, so a bucket of one large component and few others is dealt out
    about once.
    """
    sizes = buckets.groupBy("key").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("row")).alias("mark"), F.sum(F.xxhash64("row", F.lit(1)) % 1_000_003).alias("sum"))
    once = sizes.groupBy("n", "mark", "sum").agg(F.min("key").alias("key"))  # of bands with the same rows, one
    half = block // 2
    common = buckets.groupBy("key", "root").agg(F.count("*").alias("m")).where(F.col("m") > half)
    rest = common.groupBy("key").agg(F.sum("m").alias("in_common"))
    cuts = once.select("key", "n").join(rest, "key", "left").withColumn("cuts", F.ceil((F.col("n") - F.coalesce("in_common", F.lit(0))) / half).cast("int"))
    placed = buckets.join(redealt(cuts.select("key", "cuts"), "key"), "key").join(redealt(common, "key"), ["key", "root"], "left")
    # a block: its root (null for rows of several roots) and a number
    own = F.when(F.col("m").isNull(), F.pmod(F.xxhash64("root"), F.col("cuts"))).otherwise(F.pmod(F.xxhash64("row"), F.ceil(F.col("m") / half)))
    placed = placed.withColumn("of", F.when(F.col("m").isNotNull(), F.col("root"))).withColumn("own", own.cast("long"))
    placed = materialise(placed.select("row", "root", "key", F.struct("of", "own").alias("block")), "shingle-blocks")
    blocks = materialise(placed.select("key", "block").distinct(), "shingle-block-names")
    other = blocks.where("block.of is null").select("key", F.col("block").alias("i"))
    every, whole = blocks.select("key", F.col("block").alias("j")), blocks.where("block.of is not null")
    mixed = other.join(every, "key").where("j.of is not null or i <= j")
    several = whole.groupBy("key").agg(F.min("block.of").alias("low"), F.max("block.of").alias("high")).where("low <> high").select("key")
    apart = whole.select("key", F.col("block").alias("i")).join(several, "key").join(every, "key").where("i < j and j.of <> i.of")
    ends = mixed.union(apart).select("key", F.xxhash64("i").alias("x"), F.xxhash64("j").alias("y"), F.explode(F.array_distinct(F.array("i", "j"))).alias("block"))
    asked = placed.join(redealt(ends, "key"), ["key", "block"]).select("row", "root", "key", F.col("x").alias("i"), F.col("y").alias("j"))
    keys = ["key", "i", "j"]
    tasks = asked.join(sets, "row").select(*keys, "row", "root", "fp", "held").repartition(*keys).sortWithinPartitions(*keys)

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for batch in batches:
            yield from zip(*(c.to_pylist() for c in batch.columns), strict=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, part in groupby(members(batches), key=lambda x: x[:3]):
            rows, root, fps, held = zip(*(x[3:] for x in part), strict=True)
            held = [np.frombuffer(x, np.uint64) for x in held]
            pairs = links_in_groups(np.array(fps, np.int64).view(np.uint64), np.zeros(len(rows), np.int64), WIDE, lambda a, b, held=held: jaccard(held[a], held[b]) >= similar, np.array(root, np.int64))
            if pairs:
                yield pa.RecordBatch.from_pydict({"a": pa.array([rows[a] for a, _ in pairs], pa.int64()), "b": pa.array([rows[b] for _, b in pairs], pa.int64())})

    return tasks.mapInArrow(run, "a long, b long")


def fingerprint_pairs(firsts: DataFrame, radius: int) -> DataFrame:
    """(row, fp) -> (a, b): pairs of rows, of equal fingerprints or of ones that links within the radius connect."""
    distinct = materialise(firsts.groupBy("fp").agg(F.min("row").alias("hub")), "shingle-fingerprints")
    same = firsts.join(redealt(distinct, "fp"), "fp").where("row <> hub").select(F.col("row").alias("a"), F.col("hub").alias("b"))
    links = materialise(fingerprint_links(distinct.select("fp"), radius), "shingle-near")
    ends = links.join(distinct.select(F.col("fp").alias("a"), F.col("hub").alias("row_a")), "a").join(distinct.select(F.col("fp").alias("b"), F.col("hub").alias("row_b")), "b")
    return same.union(ends.select(F.col("row_a").alias("a"), F.col("row_b").alias("b")))


def similar_groups(docs: DataFrame, row_col: str, text_col: str = "text", shingle: int = 5, similar: float = 0.8, radius: int = 3) -> DataFrame:
    """(row, root) of every row of docs: rows that links of similar sets of word shingles connect have one root.

    row_col: distinct longs, in a table that was written after they were given. Rows of equal sets are linked too.
    Candidates are the SimHash links of the sets within the radius, and rows of one bucket of bands; both are checked.
    Each bucket's rows are first held against its least row, which joins large groups of copies at a cost in proportion
    to their size; buckets that are not one component then are compared whole.
    """
    texts = docs.select(F.col(row_col).alias("row"), F.col(text_col).cast("string").alias("text"))

    def marks(batch: pa.RecordBatch) -> dict:
        digest, keys, fps = [], [], []
        for text in texts_of(batch.column(1)):
            held = shingle_set(text, shingle)
            digest.append(xxhash.xxh128_digest(held.tobytes(), SEED))
            fps.append(majority(iter([held])))
            keys.append(band_keys(held).view(np.int64) if len(held) else [])
        return {"row": batch.column(0), "digest": pa.array(digest, pa.binary()), "fp": pa.array(np.array(fps, np.uint64).view(np.int64)), "keys": pa.array(keys, pa.list_(pa.int64()))}

    def whole(batch: pa.RecordBatch) -> dict:
        held = [shingle_set(x, shingle) for x in texts_of(batch.column(1))]
        fps = np.array([majority(iter([x])) for x in held], np.uint64).view(np.int64)
        return {"row": batch.column(0), "fp": pa.array(fps), "held": pa.array([x.tobytes() for x in held], pa.binary())}

    marked = materialise(arrow_map(texts, marks, "row long, digest binary, fp long, keys array<long>"), "shingle-marks")
    firsts = materialise(marked.groupBy("digest").agg(F.min("row").alias("row"), F.first("fp").alias("fp")), "shingle-sets")
    near = materialise(fingerprint_pairs(firsts.select("row", "fp"), radius), "shingle-candidates")
    dealt = marked.join(firsts.select("row"), "row", "left_semi").select("row", F.explode("keys").alias("key"))
    shared = dealt.groupBy("key").agg(F.count("*").alias("n"), F.min("row").alias("hub")).where("n > 1").drop("n")
    buckets = materialise(dealt.join(redealt(shared, "key"), "key").select("row", "key", "hub"), "shingle-buckets")
    sets = materialise(arrow_map(texts.join(buckets.select("row").union(near.select("a")).union(near.select("b")).distinct(), "row"), whole, "row long, fp long, held binary"), "shingle-held")
    banded = buckets.where("row <> hub").select(F.col("row").alias("a"), F.col("hub").alias("b"))
    stars = materialise(sure_links(banded.union(near).distinct(), sets, similar), "shingle-stars")
    roots = connected_components(stars)
    rooted = buckets.join(redealt(roots, "node"), F.col("row") == F.col("node"), "left").select("row", "key", F.coalesce("root", "row").alias("root"))
    rooted = materialise(rooted, "shingle-rooted")
    split = rooted.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("key")
    rest = materialise(similar_links(sets, rooted.join(redealt(split, "key"), "key"), similar), "shingle-links")
    if not rest.isEmpty():
        roots = connected_components(stars.union(rest))
    named = firsts.join(roots, F.col("row") == F.col("node"), "left").select("digest", F.coalesce("root", "row").alias("root"))
    return marked.select("row", "digest").join(redealt(named, "digest"), "digest").select("row", "root")
