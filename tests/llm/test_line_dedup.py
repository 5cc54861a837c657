import random

from linform.llm import line_dedup as L


def brute(rows, min_words):
    """Later copies of repeated runs, by comparing all pairs of positions."""
    docs = sorted({(d, t or "") for d, t in rows}, key=lambda x: (x[0] is None, x[0] or 0))
    lines, split = [], {}
    for n, (_, t) in enumerate(docs):
        split[n] = t.split("\n")
        lines.append([(i, x) for i, x in enumerate(split[n]) if x.strip()])
    flat = [(n, p) for n in range(len(docs)) for p in range(len(lines[n]))]
    gone = {n: set() for n in range(len(docs))}
    for k, (n, p) in enumerate(flat):
        best = 0
        for m, q in flat[:k]:
            e = 0
            while p + e < len(lines[n]) and q + e < len(lines[m]) and lines[n][p + e][1] == lines[m][q + e][1]:
                e += 1
            best = max(best, e)
        if best and sum(len(lines[n][p + e][1].split()) for e in range(best)) >= min_words:
            gone[n] |= {lines[n][p + e][0] for e in range(best)}
    out = {}
    for n, (d, t) in enumerate(docs):
        out[d, t] = ("\n".join(x for i, x in enumerate(split[n]) if i not in gone[n]), len(gone[n]))
    return sorted(((d, *out[d, t or ""]) for d, t in rows), key=str)


def test_against_all_pairs(spark):
    rng = random.Random(11)
    for trial in range(3):
        pool = [" ".join(f"w{rng.randrange(40)}" for _ in range(rng.choice([1, 2, 5, 9]))) for _ in range(8 + 20 * trial)] + ["", "  ", "\t", "\r", "a\t\tb ", "\u00a0 c\r"]
        rows = []
        for d in range(24):
            lines = [rng.choice(pool) if rng.random() < 0.6 else f"only {d} {i}" for i in range(rng.randrange(0, 14))]
            rows.append((d, "\n".join(lines)))
        block = "\n".join(f"line {i} of a passage" for i in range(11))
        rows += [(30, f"x\n{block}\ny"), (31, block), (None, f"{block}\nend"), (32, None), (33, ""), (34, "same line\n" * 40), rows[3], (35, f"y\n{block[:60]}")]
        rows += [(36 + i, "one line that is the same in many\n" + f"apart {i}") for i in range(30)]
        df = spark.createDataFrame([(*r, "c") for r in rows], "doc_id long, text string, gone string").repartition(4)
        got = L.dedup_lines(df, min_words=12)
        assert got.columns == ["doc_id", "text", "n_lines", "n_deleted"]
        assert sorted(((r.doc_id, r.text or "", r.n_deleted) for r in got.collect()), key=str) == brute(rows, 12)


def test_words_are_counted_alike_for_all_line_ends(spark):
    short = "Read more"
    for end, inner in (("\r", " "), ("", " "), ("", "\t"), ("\t ", "\t\t"), ("\r", "  ")):
        line = short.replace(" ", inner) + end
        rows = [(i, f"text {i}{end}\n{line}\n") for i in range(30)]
        got = L.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), min_words=3).collect()
        assert all(r.n_deleted == 0 for r in got)
        got = L.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), min_words=2).collect()
        assert sorted(r.n_deleted for r in got) == [0] + [1] * 29


def test_ranks_are_those_of_sorted_suffixes(spark):
    rng = random.Random(3)
    rows = [(d, "\n".join(rng.choice("ab") for _ in range(30))) for d in range(6)]
    df = L.keyed(spark.createDataFrame(rows, "doc_id long, text string"))
    lines = L.repeated_lines(df.select("kid", "dk", "_text")).cache()
    order = {r.l0: r.n for n, r in enumerate(lines.select("l0", "l1").distinct().orderBy("l0", "l1").collect()) for r in [type("R", (), {"l0": r.l0, "n": n})]}
    name = {(r.kid, r.pos): order[r.l0] for r in lines.collect()}
    for k, level in enumerate(L.suffix_levels(lines, 8)):
        ranks = {(r.kid, r.pos): r.r for r in level.collect()}
        runs = {at: tuple(name.get((at[0], at[1] + i)) for i in range(1 << k)) for at in name}
        runs = {at: x for at, x in runs.items() if None not in x}
        often = {x for x in runs.values() if list(runs.values()).count(x) > 1}
        assert set(ranks) == {at for at, x in runs.items() if x in often or k == 0}
        by_rank = [runs[at] for at in sorted(ranks, key=ranks.get)]
        assert by_rank == sorted(by_rank) and len(set(ranks.values())) == len({runs[at] for at in ranks})


def test_lines_of_a_maximal_run_share_a_number(spark):
    block = [f"line {i} of a long passage" for i in range(9)]
    rows = [(1, "\n".join(["x", *block])), (2, "\n".join([*block[:5], "own", *block])), (3, "\n".join(block[4:]))]
    df = L.keyed(spark.createDataFrame(rows, "doc_id long, text string"))
    got = {}
    for r in L.repeated_runs(L.repeated_lines(df.select("kid", "dk", "_text")), 12).collect():
        got.setdefault((r.kid, r.run), []).append(r.at)
    assert sorted((k[0], sorted(v)) for k, v in got.items()) == [(2, list(range(5))), (2, list(range(6, 15))), (3, list(range(5)))]


def test_edges(spark):
    df = spark.createDataFrame([(1, "a b c"), (2, None)], "doc_id long, text string")
    assert sorted((r.doc_id, r.text, r.n_deleted) for r in L.dedup_lines(df).collect()) == [(1, "a b c", 0), (2, None, 0)]
    assert L.dedup_lines(df.limit(0)).count() == 0
    long = "\n".join(f"row {i} with some more words in it" for i in range(300))
    out = L.dedup_lines(spark.createDataFrame([(1, long), (2, long), (3, "z\n" + long)], "doc_id long, text string")).collect()
    assert sorted((r.doc_id, r.text) for r in out) == [(1, long), (2, ""), (3, "z")]
    assert "Python" not in L.dedup_lines(df)._jdf.queryExecution().toString()
