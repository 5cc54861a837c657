import os
import sys

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

import corpus_pipeline as P
from linform.llm import mixing, simhash
from linform.llm.common import materialise

D = "/root/testdata/sf0.001"


def test_stages_against_brute_force(spark):
    from test_line_dedup import brute
    from test_simhash import roots

    docs = P.table(spark, D, "documents").select(*P.COLUMNS)
    kept = []
    for _, stage in P.STAGES:
        docs = materialise(stage(spark, docs, D), "test-stage")
        kept.append(docs.collect())
    quality, lines, near, mixed, tokens = kept
    every = P.table(spark, D, "documents").collect()
    assert all(set(r.asDict()) == set(P.COLUMNS) for part in kept[:4] for r in part[:3])
    assert 0 < len(quality) < len(every) and {(r.doc_id, r.text) for r in quality} <= {(r.doc_id, r.text) for r in every}

    want = brute([(r.doc_id, r.text) for r in quality], 20)
    assert sorted(((r.doc_id, r.text) for r in lines), key=str) == sorted(((d, t) for d, t, n in want if not n or t.strip()), key=str)
    assert all(r.n_chars == len(r.text) for r in lines)

    sets = [simhash.shingle_set(r.text or "", 5) for r in lines]
    root = roots(len(lines), [(i, j) for i in range(len(lines)) for j in range(i) if len(sets[i]) and simhash.jaccard(sets[i], sets[j]) >= 0.8 or len(sets[i]) == len(sets[j]) == 0])
    least = {}
    for r, g in zip(lines, root, strict=True):
        least[g] = min(least.get(g, r.doc_id), r.doc_id)
    assert sorted(r.doc_id for r in near) == sorted(least.values())

    labels = {r.doc_id: r for r in P.table(spark, D, "labels").collect()}
    out = {r.doc_id for r in mixed}
    clean = [r.doc_id for r in near if r.doc_id in labels and labels[r.doc_id].quality == 1 and labels[r.doc_id].toxic == 0]
    assert out <= {r.doc_id for r in near} and len(set(clean) - out) <= 0.02 * len(clean)

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    text = {r.doc_id: r.text for r in mixed}
    assert len(tokens) == len(mixed)
    for r in tokens:
        assert r.round_trip and r.ids == library.encode(text[r.doc_id], add_special_tokens=False).ids and r.n_tokens == len(r.ids)


def test_empty_documents_table(spark):
    empty = P.table(spark, D, "documents").select(*P.COLUMNS).limit(0)
    for _, stage in P.STAGES:
        assert stage(spark, empty, D).count() == 0


def test_mixing_stage_against_a_direct_solver(spark):
    """Copies of the mixing stage follow from rates that a dense solver finds in memory."""
    docs = P.table(spark, D, "documents").select(*P.COLUMNS)
    corpus = P.table(spark, D, "documents")
    weights = mixing.train(corpus, mixing.known_domains(corpus, P.table(spark, D, "labels")))
    rows = mixing.posteriors(docs, weights).collect()
    p, tokens = np.array([r.posterior for r in rows]), np.array([r.tokens for r in rows], float)
    now = tokens @ p
    total, share, clean = now.sum(), now / now.sum(), [d for d, n in enumerate(mixing.DOMAINS) if n.startswith("clean")]
    floor = (p[:, clean].sum(axis=1) >= 0.5) * 1.0
    wanted = np.array([share[d] ** 0.95 if d in clean else 0.0 for d in range(len(share))])
    wanted *= share[clean].sum() / wanted.sum()
    wanted[mixing.DOMAINS.index("low")] = share[mixing.DOMAINS.index("low")] / 2
    wanted /= wanted.sum()
    target = wanted * max(1.0, *(share[d] / wanted[d] for d in clean))
    t, rate = tokens / total, np.maximum(1.0, floor)
    weight = p / np.sqrt(share)
    top = np.linalg.eigvalsh((weight.T * t) @ weight).max() + mixing.PULL
    ahead, k = rate, 1.0
    for _ in range(60_000):  # accelerated projected gradient in the rates themselves
        new = np.maximum(floor, ahead - (p @ (((t * ahead) @ p - target) / share) + mixing.PULL * (ahead - 1)) / top)
        k_new = (1 + np.sqrt(1 + 4 * k * k)) / 2
        ahead, rate, k = new + (k - 1) / k_new * (new - rate), new, k_new
    got = {r.doc_id: r for r in mixing.mix(docs, weights, keep_clean=True, temper=0.95).collect()}
    assert max(abs(got[r.doc_id].rate - x) for r, x in zip(rows, rate, strict=True)) < 0.05
    out = {}
    for r in P.mix_domains(spark, docs, D).collect():
        out[r.doc_id] = out.get(r.doc_id, 0) + 1
    assert out == {d: r.copies for d, r in got.items() if r.copies}
    assert all(int(r.rate) <= r.copies <= int(r.rate) + 1 for r in got.values())


def test_nulls_and_repeats(spark):
    docs = spark.createDataFrame([(1, None, None, None, None), (None, "", None, None, None), (2, "some text", "en", "s", 9), (2, "some text", "en", "s", 9)], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in P.STAGES:
        got = stage(spark, docs, D).collect()
        assert 0 < len(got) and {r.doc_id for r in got} <= {1, 2, None}
        assert len(got) <= 4 or stage is P.mix_domains  # only mixing makes copies


def test_edited_copies_leave_at_similarity_four_fifths(spark):
    words = [f"w{i * i % 977}" for i in range(200)]
    edited = [f"other{i}" if i in (30, 75, 120, 165) else w for i, w in enumerate(words)]
    half = words[:100] + [f"v{i}" for i in range(100)]
    assert (simhash.fingerprint(" ".join(words)) ^ simhash.fingerprint(" ".join(edited))).bit_count() > 3
    docs = spark.createDataFrame([(i, " ".join(w), "en", "s", 1) for i, w in enumerate((words, edited, half))], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in P.drop_near_duplicates(spark, docs, D).collect()) == [0, 2]


def test_one_row_of_each_group_stays(spark):
    text = " ".join(f"w{i}" for i in range(60))
    rows = [(7, text), (7, text), (7, "another text that is long enough to stand alone"), (9, text), (None, text), (None, "a text of null ids only, in two rows"), (None, "a text of null ids only, in two rows")]
    docs = spark.createDataFrame([(d, t, "en", "s", 1) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    got = P.drop_near_duplicates(spark, docs, D).collect()
    assert sorted(((r.doc_id, r.text) for r in got), key=str) == sorted([rows[0], rows[2], rows[5]], key=str)
