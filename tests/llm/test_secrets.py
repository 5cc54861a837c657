import hashlib
import random
import re

from linform.llm import secrets as S


def brute(text):
    out = []
    for k, (p, g, n) in enumerate(((S.ASSIGN, 2, 8), (S.ACCESS, 0, 16), (S.HEX, 0, 32))):
        out += [(m.start(), k, m.end()) for m in re.finditer(p, text) if len(m[g]) >= n]
    return ",".join(f"{S.KINDS[k]}:{a}:{b}" for a, k, b in sorted(out))


RANDOM = "Zk3vQ9xT7bLm2RwY8sNd"
CASES = [
    "token: secret: abcdefgh1", "password = 'hunter2hunter2'", "API_KEY:abcdefgh apikey=12345678 ToKen=short", "paſſword=abcdefgh ſecret=12345678",
    "AKIAABCDEFGHIJKL AKIASHORT AKIAAKIAABCDEFGHIJ", "é" * 5 + "f" * 33 + " " + "0" * 31, "secret=" + "a1" * 20, "", None, f"x {RANDOM} y", "token=" + "deadbeef" * 4 + "\npasswd:\t12345678", "secret=KKKKKKKKK",
]


def test_base_spans_equal_plain_matching():
    for t in CASES:
        got = ",".join(f"{S.KINDS[k]}:{a}:{b}" for a, k, b, _ in S.base_spans(t or ""))
        assert got == brute(t or "")
    assert S.base_spans("paſſword=abcdefgh ſecret=12345678") == []


def test_ownership_separates_examples_from_owned(spark):
    shared = "Qm4vX8cT1bLk6RwY3sPz"
    rows = [(i, c, "one") for i, c in enumerate(CASES)]
    rows += [(100 + i, f"see {shared} and password=example123", f"s{i % 7}") for i in range(40)]
    rows += [(200, f"again {RANDOM}", "one"), (None, "token=abcdefgh99", None), (200, f"again {RANDOM}", "one")]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, text string, source string, held string").repartition(3)
    got = S.scan_secrets(df).collect()
    assert len(got) == len(rows)
    want = sorted((d if d is not None else -9, hashlib.sha256(brute(t or "").encode()).hexdigest()) for d, t, _ in rows)
    assert sorted((r.doc_id if r.doc_id is not None else -9, r.base_sha256) for r in got) == want
    by = {r.doc_id: r for r in got}
    assert by[9].spans == "owned:2:22" and by[200].spans == "owned:6:26" and by[9].n_owned == 1
    assert by[100].spans == "assign:29:48" and by[100].n_example == 1 and by[100].n_owned == 0
    assert by[1].n_live == 0 and by[2].n_live == 2  # repeated halves are not random
    for r in got:
        assert r.n_assign + r.n_access + r.n_hex + r.n_owned == len([x for x in r.spans.split(",") if x])
    assert S.scan_secrets(df.limit(0)).count() == 0


def test_value_in_many_repositories_of_one_owner_is_an_example(spark):
    copied = "Hk2nW9yR4jMd7QzX5tVb"
    rows = [(i, f"see {copied} and token={copied}x", "one") for i in range(S.MAX_REPOS + 1)]
    rows += [(500 + i, f"key {RANDOM} and token={RANDOM}x", "one") for i in range(S.MAX_REPOS)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    by = {r.doc_id: r for r in S.scan_secrets(df).collect()}
    assert all((by[i].n_owned, by[i].n_live, by[i].n_example) == (0, 0, 1) for i in range(S.MAX_REPOS + 1))
    assert by[0].repos == [S.MAX_REPOS + 1] and by[0].owners == [1]
    assert all((by[500 + i].n_owned, by[500 + i].n_live, by[500 + i].n_example) == (1, 1, 0) for i in range(S.MAX_REPOS))
    assert by[500].repos == [S.MAX_REPOS] * 2


def test_spans_against_brute_force(spark):
    """All spans and counts of a random corpus with planted values, from plain dictionaries."""
    rng = random.Random(9)
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    value = lambda n: "aB3" + "".join(rng.choice(letters) for _ in range(n))
    planted = {value(24): kind for kind in ["owned"] * 12 + ["copied"] * 4 + ["repos"] * 4}
    texts = {}
    for d in range(260):
        texts[d] = [f"source{d % 9}", [rng.choice(["plain words", "token=abcdefgh12", "AKIA" + "Q7" * 8, "ab" * 17, "x1 " * 3, "Long" * 9]) for _ in range(rng.randrange(4))]]
    for v, kind in planted.items():
        if kind == "owned":  # some repositories of one owner
            where = [d for d in texts if d % 9 == len(v) % 9][: rng.randrange(1, S.MAX_REPOS + 1)]
        elif kind == "copied":  # few repositories of several owners
            where = rng.sample(range(260), 5)
        else:  # one owner, too many repositories
            where = [d for d in texts if d % 9 == 4][: S.MAX_REPOS + 3]
        for d in where:
            texts[d][1].append(rng.choice([f"see {v} here", f"password: {v}", v]))
    rows = [(d, "\n".join(lines), source) for d, (source, lines) in texts.items()]
    found = {}
    for d, t, _ in rows:
        base = S.base_spans(t)
        found[d] = base + [(m.start(), 3, m.end(), m[0]) for m in S.BARE.finditer(t) if S.entropy(m[0]) >= 3.0 and not any(m.start() < b[2] and b[0] < m.end() for b in base)]
    repos, owners = {}, {}
    for d, _, source in rows:
        for *_, v in found[d]:
            repos.setdefault(v, set()).add(d)
            owners.setdefault(v, set()).add(source)
    few = lambda v: len(owners[v]) <= S.MAX_OWNERS and len(repos[v]) <= S.MAX_REPOS
    want, truth = {}, []
    for d in found:
        kept = sorted((a, k, b) for a, k, b, v in found[d] if k < 3 or few(v))
        live = sum(k < 3 and few(v) and S.entropy(v) >= 3.0 for a, k, b, v in found[d])
        want[d] = ",".join(f"{S.KINDS[k]}:{a}:{b}" for a, k, b in kept), live, sum(k < 3 and not few(v) for a, k, b, v in found[d])
        truth += [planted.get(v) for a, k, b, v in found[d] if k == 3 and few(v)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    got = {r.doc_id: (r.spans, r.n_live, r.n_example) for r in S.scan_secrets(df).collect()}
    assert got == want
    assert len(truth) > 20 and set(truth) == {"owned"}  # every added span is a planted value of one owner
