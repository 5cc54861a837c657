import hashlib
import math
import random

from pyspark.sql import functions as F

from linform.llm import sketch as S


def edits(rows):
    """(doc_id, text) without repeats -> their edited texts, in order."""
    keys = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0))
    out = {}
    for i, (d, t) in enumerate(keys):
        t, after = t or "", keys[(i + 1) % len(keys)][1] or ""
        half = len(t) // 2
        out[d] = (t, t[: len(t) - half] + after[:half], after)
    return out


def shingles(t):
    w = t.split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def error(j, n):
    """The stated standard error of likeness."""
    return math.sqrt(j * (1 - j) * (1 - S.FRACTION) / (S.FRACTION * max(1, n)))


def test_against_exact_sets(spark):
    rng = random.Random(3)
    rows = [(i * 3 - 20, " ".join(f"w{rng.randrange(3000)}" for _ in range(rng.choice([0, 1, 4, 5, 40, 2000])))) for i in range(90)]
    rows += [(None, "nul é🙂 " * 5), (1000, None), (1001, ""), (1002, "x"), (1003, "🙂🙂🙂"), (1004, "long words here and there " * 9000)]
    rng.shuffle(rows)
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, dk int").repartition(5)
    got = {r.doc_id: r for r in S.edited_and_next(df).collect()}
    assert len(got) == len(rows)

    for d, (t, edited, after) in edits(rows).items():
        r = got[d]
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        a = shingles(t)
        for b, near in ((shingles(edited), r.near_edited), (shingles(after), r.near_next)):
            exact = len(a & b) / len(a | b) if a | b else 1.0
            assert 0 <= near <= 1 and (near == 1 or a != b)
            assert abs(near - exact) <= 4.5 * error(exact, len(a | b)) + 1e-9 or len(a | b) < 20, (d, near, exact)
    assert S.edited_and_next(df.limit(0)).count() == 0


def test_repeated_rows_and_equal_texts(spark):
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e f"), (2, "other"), (None, None), (None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = S.edited_and_next(df).collect()
    assert len(got) == len(rows)
    assert len({r.fingerprint for r in got if r.n_chars == 11}) == 1
    assert len({(r.doc_id, r.n_chars, r.edited_sha256) for r in got}) == 4
    one = S.edited_and_next(spark.createDataFrame([(7, "abcd")], "doc_id long, text string")).first()
    assert one.edited_sha256 == hashlib.sha256(b"abab").hexdigest() and one.near_next == 1.0


def test_containment_of_unequal_texts(spark):
    rng = random.Random(5)
    words = [f"w{rng.randrange(10**6)}" for _ in range(40_000)]
    df = spark.createDataFrame([(" ".join(words[5000:7000]), " ".join(words))], "x string, y string")
    made = S.with_likeness(S.with_sketch(S.with_sketch(df, "x", "a"), "y", "b"), "a", "b", "near", "inside").first()
    assert made.inside > 0.97 and made.near < 0.1


def test_unrelated_texts_of_unequal_length(spark):
    rng = random.Random(6)
    some = lambda n: " ".join(f"w{rng.randrange(10**6)}" for _ in range(n))
    rows = [(i, some(8), some(3000)) for i in range(200)]
    df = spark.createDataFrame(rows, "i long, x string, y string").repartition(4)
    df = S.with_sketch(S.with_sketch(df, "x", "a"), "y", "b")
    got = S.with_likeness(df, "a", "b", "near", "inside").collect()
    assert max(r.near for r in got) < 0.05 and all(r.inside in (0.0, None) for r in got)
    assert any(r.inside is None for r in got) and sum(r.inside == 0 for r in got) > 100
    assert all(0.2 < len(r.b) / 2996 < 0.3 for r in got)  # one fraction at every size
    none = spark.createDataFrame([("", "a b c", " "), (None, "", "x")], "x string, y string, z string")
    made = S.with_sketch(S.with_sketch(none, "x", "a"), "y", "b")
    got = S.with_likeness(made, "a", "b", "near", "inside").collect()
    assert [(r.near, r.inside) for r in got] == [(0.0, 1.0), (1.0, 1.0)]


def test_sketches_merge(spark):
    rng = random.Random(7)
    sizes = [0, 1, 3, 6, 9, 30, 400]
    rows = [(i, [rng.randrange(-(2**63), 2**63) for _ in range(rng.choice(sizes))], [rng.randrange(-(2**63), 2**63) for _ in range(rng.choice(sizes))]) for i in range(150)]
    df = spark.createDataFrame(rows, "i long, x array<long>, y array<long>").repartition(3)
    kept = lambda c: S._kept(F.array_distinct(c), S.FRACTION)
    made = df.select(kept(F.concat("x", "y")).alias("whole"), S.merged(kept(F.col("x")), kept(F.col("y"))).alias("parts"), "x", "y").collect()
    for r in made:
        every = {h % 2**64 for h in [*r.x, *r.y]}
        want = sorted(h for h in every if h < S.FRACTION * 2**64) or sorted(every)[:1]
        assert [h % 2**64 for h in r.whole] == [h % 2**64 for h in r.parts] == want


def test_likeness_is_right_in_the_mean_by_size(spark):
    rng = random.Random(8)
    rows = []
    for n in (6, 12, 40, 200, 1500):
        for _ in range(60):
            words = [f"w{rng.randrange(10**6)}" for _ in range(n)]
            cut = n * 2 // 3
            rows.append((n, " ".join(words), " ".join(words[:cut] + [f"v{rng.randrange(10**6)}" for _ in range(n - cut)])))
    df = spark.createDataFrame(rows, "n int, x string, y string").repartition(4)
    got = S.with_likeness(S.with_sketch(S.with_sketch(df, "x", "a"), "y", "b"), "a", "b", "near").collect()
    for n in (6, 12, 40, 200, 1500):
        off, told = [], []
        for r in got:
            if r.n == n:
                a, b = shingles(r.x), shingles(r.y)
                j = len(a & b) / len(a | b)
                off.append(r.near - j)
                told.append(error(j, len(a | b)))
        spread = math.sqrt(sum(x * x for x in off) / len(off))
        assert abs(sum(off) / len(off)) < 0.12 and spread < 1.5 * max(told) + 0.02, (n, spread, max(told))


def test_no_python_in_the_plan(spark):
    df = spark.range(3).select(F.col("id").alias("doc_id"), F.lit("some text").alias("text"))
    plan = S.edited_and_next(df)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan
