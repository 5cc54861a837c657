import random

import numpy as np
import xxhash

from linform.llm import simhash as H


def slow_fingerprint(text):
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text))
    if not words:
        return 0
    runs = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hs = [xxhash.xxh64_intdigest(r.encode(), 42) for r in runs]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hs) > len(hs))


def test_fingerprint():
    rng = random.Random(2)
    cases = ["", "   ", "one", "One two", "A b C", "É É é x", "a\x85b\xa0c d\x1ce f"] + [" ".join(rng.choice("abcdefgh") for _ in range(rng.randrange(200))) for _ in range(50)]
    for t in cases:
        assert H.fingerprint(t) == slow_fingerprint(t)
    long = "x y z w " * 60_000
    assert H.fingerprint(long) == slow_fingerprint(long)


def roots(n, pairs):
    r = list(range(n))

    def find(x):
        while r[x] != x:
            x = r[x]
        return x

    for a, b in pairs:
        r[find(max(a, b))] = r[find(min(a, b))] = min(find(a), find(b))
    return [find(i) for i in range(n)]


def test_planes_find_all_links():
    rng = np.random.default_rng(4)
    for radius in (1, 3, 5):
        centre = rng.integers(0, 1 << 63, 12, dtype=np.uint64)
        values = np.array([c ^ np.uint64(sum(1 << int(k) for k in rng.choice(64, int(rng.integers(0, 7)), replace=False))) for c in rng.choice(centre, 700)], np.uint64)
        group = np.sort(rng.integers(0, 5, 700))
        want = [(i, j) for i in range(700) for j in range(i) if group[i] == group[j] and int(values[i] ^ values[j]).bit_count() <= radius]
        got = H.links_in_groups(values, group, radius)
        assert all(int(values[i] ^ values[j]).bit_count() <= radius and group[i] == group[j] for i, j in got)
        assert roots(700, got) == roots(700, want)


def test_large_groups_of_one_component_and_few_others():
    rng = np.random.default_rng(6)
    for n, strange in ((600, 5), (900, 60), (900, 0), (700, 400)):
        flips = [np.uint64(sum(1 << int(k) for k in rng.choice(64, int(rng.integers(0, 3)), replace=False))) for _ in range(n)]
        values = np.array([np.uint64(0x0F0F0F0F0F0F0F0F) ^ f for f in flips], np.uint64)
        far = rng.integers(0, 1 << 63, 1 + strange // 4, dtype=np.uint64)
        for i in rng.choice(n, strange, replace=False):
            values[i] = rng.choice(far) ^ np.uint64(1 << int(rng.integers(0, 64)))
        group = np.zeros(n, np.int64)
        want = [(i, j) for i in range(n) for j in range(i) if int(values[i] ^ values[j]).bit_count() <= 3]
        assert roots(n, H.links_in_groups(values, group, 3)) == roots(n, want)
        known = np.array([0 if v ^ np.uint64(0x0F0F0F0F0F0F0F0F) < 2**63 else i + 1 for i, v in enumerate(values)])
        tied = [(i, int(np.flatnonzero(known == known[i])[0])) for i in range(n)]
        assert roots(n, H.links_in_groups(values, group, 3, known=known) + tied) == roots(n, want + tied)


def test_masks_lose_no_pair():
    rng = random.Random(6)
    for count in (10, 10**7, 10**12):
        masks = H.block_masks(count, 3)
        for _ in range(500):
            a = rng.getrandbits(64)
            b = a ^ sum(1 << k for k in rng.sample(range(64), 3))
            assert any(a & m == b & m for m in masks)
    assert len(H.block_masks(10, 3)) == 4 < len(H.block_masks(10**12, 3))


def test_components_against_all_pairs(spark):
    rng = random.Random(9)
    rows = []
    for i in range(120):
        words = [f"w{rng.randrange(500)}" for _ in range(rng.randrange(3, 300))]
        rows.append((3 * i + 1, " ".join(words)))
        if i % 4 == 0:
            words[len(words) // 2] = "changed"
            rows.append((3 * i, " ".join(words)))
    rows += [(1000 + i, "the very same words in all of these") for i in range(200)] + [(5000, None), (4999, ""), (None, " "), (None, "lone words here"), (7, "x")]
    df = spark.createDataFrame([(*r, 0) for r in rows], "doc_id long, text string, fp int").repartition(4)
    got = H.near_duplicates(df).collect()
    fps = [H.fingerprint(t or "") for _, t in rows]
    root = roots(len(rows), [(i, j) for i in range(len(rows)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 3])
    least = {}
    for (d, _), r in zip(rows, root, strict=True):
        least[r] = min((x for x in (d, least.get(r)) if x is not None), default=None)
    want = sorted((str(d), f"{f:016x}", str(least[r])) for (d, _), f, r in zip(rows, fps, root, strict=True))
    assert sorted((str(r.doc_id), r.fingerprint, str(r.component_id)) for r in got) == want
    assert H.near_duplicates(df.limit(0)).count() == 0


def test_large_buckets_are_cut_without_loss(spark):
    rng = random.Random(3)
    centre = rng.getrandbits(63)
    fps = sorted({centre ^ sum(1 << k for k in rng.sample(range(63), rng.randrange(5))) for _ in range(400)})
    df = spark.createDataFrame([(f,) for f in fps], "fp long")
    got = H.fingerprint_links(df, 3, block=50).collect()
    at = {f: i for i, f in enumerate(fps)}
    want = [(i, j) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 3]
    assert roots(len(fps), [(at[r.a], at[r.b]) for r in got]) == roots(len(fps), want)


def test_similar_groups_link_by_fingerprints(spark):
    """Similar texts within the radius are candidates by their fingerprints, without the bands."""
    words = [f"w{i * i % 977}" for i in range(3000)]
    edited = [*words[:-1], "other"]
    sets = [H.shingle_set(" ".join(w), 5) for w in (words, edited)]
    assert (H.majority(iter([sets[0]])) ^ H.majority(iter([sets[1]]))).bit_count() <= 3
    df = spark.createDataFrame([(0, " ".join(words)), (1, " ".join(edited)), (2, "quite another text of some more words")], "row long, text string")
    first = H.materialise(df, "test-rows")
    fps = spark.createDataFrame([(r, H.majority(iter([s])) - (1 << 64 if H.majority(iter([s])) >> 63 else 0)) for r, s in enumerate(sets)], "row long, fp long")
    assert [sorted(x) for x in H.fingerprint_pairs(fps, 3).collect()] == [[0, 1]]
    roots = {r.row: r.root for r in H.similar_groups(first, "row").collect()}
    assert roots[0] == roots[1] != roots[2]


def test_similar_groups_against_all_pairs(spark):
    rng = random.Random(11)
    rows = []
    for _ in range(150):
        words = [f"w{rng.randrange(3000)}" for _ in range(rng.choice([3, 8, 12, 40, 150, 400]))]
        rows.append(" ".join(words))
        for _ in range(rng.randrange(3)):
            for _ in range(rng.randrange(1, 2 + len(words) // 60)):
                words[rng.randrange(len(words))] = f"edit{rng.randrange(10**6)}"
            rows.append(" ".join(words))
    rows += [None, "", " ", "a b c", "A b  c"] + ["one line of five words or more " * k for k in (2, 9, 90)]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} - {()} for w in ((t or "").lower().split() for t in rows)]
    like = [(i, j, len(a & b) / max(1, len(a | b)) if a or b else 1.0) for i, a in enumerate(sets) for j, b in enumerate(sets[:i])]
    fps = [H.fingerprint(t or "") for t in rows]
    far = [(i, j) for i, j, x in like if x >= 0.8 and (fps[i] ^ fps[j]).bit_count() > 3]
    assert len(far) > 30  # out of reach of three-word fingerprints at radius 3
    want = roots(len(rows), [(i, j) for i, j, x in like if x >= 0.8])
    df = spark.createDataFrame(list(enumerate(rows)), "row long, text string").repartition(3)
    got = {r.row: r.root for r in H.similar_groups(df, "row").collect()}
    assert [min(k for k in got if got[k] == got[i]) for i in range(len(rows))] == want
    assert H.similar_groups(df.limit(0), "row").count() == 0


def test_similar_links_of_cut_buckets(spark):
    rng = random.Random(5)
    base = np.array([rng.getrandbits(64) for _ in range(60)], np.uint64)
    held = [np.unique(np.append(rng.sample(list(base), 57), np.array([rng.getrandbits(64)], np.uint64)).astype(np.uint64)) for _ in range(200)]
    rows = [(i, int(np.uint64(H.majority(iter([x]))).view(np.int64)), x.tobytes()) for i, x in enumerate(held)]
    sets = spark.createDataFrame(rows, "row long, fp long, held binary")
    want = [(i, j) for i in range(200) for j in range(i) if H.jaccard(held[i], held[j]) >= 0.8]
    for known in (lambda i: i, lambda i: 0 if i < 120 else i, lambda i: i % 3 if i < 150 else i):  # none, one or three large components
        buckets = spark.createDataFrame([(i, 7, known(i)) for i in range(200)], "row long, key long, root long")
        got = [(r.a, r.b) for r in H.similar_links(sets, buckets, 0.8, block=40).collect()]
        tied = [(i, known(i)) for i in range(200)]
        assert roots(200, got + tied) == roots(200, want + tied)


def test_large_group_of_near_copies(spark):
    rng = random.Random(12)
    words = [f"w{rng.randrange(5000)}" for _ in range(120)]
    rows = []
    for i in range(1500):
        copy = list(words)
        copy[rng.randrange(120)] = f"edit{i}"
        rows.append(" ".join(copy))
    bridge = words[:100] + [f"b{k}" for k in range(16)]
    rows += [" ".join(bridge), " ".join(words[:90]), "alone " * 3]
    sets = [H.shingle_set(t, 5) for t in rows]
    df = spark.createDataFrame(list(enumerate(rows)), "row long, text string").repartition(4)
    got = {r.row: r.root for r in H.similar_groups(df, "row").collect()}
    assert len(got) == len(rows) and len({got[i] for i in range(1500)}) == 1
    for i in (1500, 1501, 1502):
        near = any(H.jaccard(sets[i], sets[j]) >= 0.8 for j in range(1500))
        assert (got[i] == got[0]) == near
