import hashlib
import random

from pyspark.sql import functions as F

from linform.llm import exact_dedup as X


def test_cuckoo_index_with_deletes_and_growth():
    rng, index, live = random.Random(3), X.CuckooIndex(2), {}
    for i in range(6000):
        key = hashlib.sha256(str(rng.randrange(3000)).encode()).digest()
        if key in live and rng.random() < 0.5:
            assert index.delete(key)
            del live[key]
        elif key not in live:
            index.insert(key, i)
            live[key] = i
        assert (index.get(key) is not None) == (key in live)
    assert dict(index.items()) == live and index.resizes > 3 and index.live == len(live)
    assert not index.delete(b"\0" * 32)


def test_hits_are_verified_in_their_buckets():
    rng, index = random.Random(4), X.CuckooIndex(4)
    alike = [b"\1\2" + b"\0" * 8 + bytes([i]) * 30 for i in range(6)]  # one mark, one pair of buckets
    for i, key in enumerate(alike[:5]):
        assert index.get(key) is None
        index.insert(key, i)
    assert index.false_hits >= 10 and index.maybe(alike[5]) and index.get(alike[5]) is None
    assert [index.get(k) for k in alike[:5]] == list(range(5))
    assert index.delete(alike[2]) and not index.delete(alike[2]) and [index.get(k) for k in alike[:5]] == [0, 1, None, 3, 4]
    for key in (hashlib.sha256(rng.randbytes(9)).digest() for _ in range(500)):  # overflow: grows from the stored keys
        index.insert(key, key)
    assert index.resizes > 2 and index.live == 504 and all(v is k or v in range(5) for k, v in index.items())


def test_parts_handed_on_early_make_the_same_index(spark):
    df = spark.range(4000).select(F.col("id").alias("doc_id"), (F.col("id") % 701).cast("string").alias("text")).repartition(3)
    digested = X.digests(df)
    key = lambda index: sorted(map(tuple, index.select("digest", "keep_id", "group_size").collect()))
    assert key(X.build_index(digested)) == key(X.build_index(digested, flush=50, part=64))


def brute(rows):
    groups = {}
    for i, (d, t) in enumerate(rows):
        groups.setdefault((t or "").encode().lower(), []).append((d is not None, d or 0, i))
    out = []
    for i, (d, t) in enumerate(rows):
        g = groups[(t or "").encode().lower()]
        best = max(g)
        out.append((d, best[1] if best[0] else None, len(g), hashlib.sha256((t or "").encode().lower()).hexdigest()))
    return sorted(out, key=str)


def test_against_brute_force(spark):
    rows = [(1, "Abc"), (2, "aBC"), (3, None), (4, ""), (None, "abc"), (None, "É"), (5, "é"), (6, "x" * 100_000), (7, "X" * 100_000), (8, "ß"), (9, "ß")]
    rows += [(100 + i, "hot") for i in range(400)] + [(9, "ß"), (None, "lone")]
    df = spark.createDataFrame([(*r, "z") for r in rows], "doc_id long, text string, digest string").repartition(5)
    got = X.exact_duplicates(df).collect()
    assert sorted(((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in got), key=str) == brute(rows)
    assert sum(r.kept for r in got) == len({r.text_sha256 for r in got})
    assert X.exact_duplicates(df.limit(0)).count() == 0


def test_changes(spark):
    df = spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "doc_id long, text string")
    first = X.digests(df)
    new = X.digests(spark.createDataFrame([(9, "a"), (10, "d")], "doc_id long, text string"))
    gone = first.where("doc_id = 2").select("digest")
    got = X.apply_changes(X.build_index(first), new, gone).collect()
    assert sorted((r.keep_id, r.group_size) for r in got) == [(3, 1), (9, 2), (10, 1)]
