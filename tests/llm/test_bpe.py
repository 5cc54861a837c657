import hashlib
import random

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from linform.llm import bpe

PATH = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def machine():
    return bpe.MergeAutomaton.from_file(PATH)


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def texts():
    rng = random.Random(5)
    pool = ["the", " the", "ing", "aaaa", "  ", "\n", "\t", "é", "ß", "日本", "🙂", "'s", "'ll", "1234", "#!", "<|endoftext|>", " <|endoftext|>", "Qu", "eau", "\x1c", "\x85", "　", "zzz", "é", "​", "٣", "_", "²", "½", "Ⅷ", "一", "\x1f", "ͅ", "𝟘", "a_b", "\r\n"]
    for _ in range(1500):
        yield "".join(rng.choice(pool) for _ in range(rng.randrange(12)))
    for _ in range(1500):
        yield "".join(chr(rng.choice([rng.randrange(32, 127), rng.randrange(97, 123), rng.randrange(160, 1500)])) for _ in range(rng.randrange(40)))
    for _ in range(1500):
        yield "".join(rng.choice(["the", " ", "\n", "\t", "\x0b", "\x1c", "\x1f", "'s", "'ll", "12", "_", "#!", "a", "\r"]) for _ in range(rng.randrange(12)))
    yield from ("", " ", "a" * 3001, " " * 2000, "ab" * 2500, "=" * 999, "<|endoftext|><|endoftext|>x")


def test_ids_equal_the_library(machine, library):
    for t in texts():
        got = machine.encode(t)
        assert got == library.encode(t, add_special_tokens=False).ids, repr(t)
        assert machine.decode(got) == t == library.decode(got, skip_special_tokens=False)


def test_small_merge_lists_against_direct_merging():
    """Every machine for a random merge list spells what merging by rank gives."""
    rng = random.Random(1)
    for _ in range(60):
        tokens, merges = ["a", "b", "c"], []
        for _ in range(rng.randrange(1, 9)):
            pair = rng.choice(tokens), rng.choice(tokens)
            if "".join(pair) not in tokens:
                merges.append(pair)
                tokens.append("".join(pair))
        tool = bpe.MergeAutomaton({t: i for i, t in enumerate(tokens)}, merges)
        for _ in range(60):
            word = "".join(rng.choice("abc") for _ in range(rng.randrange(1, 14)))
            parts = list(word)
            for a, b in merges:
                i = 0
                while i + 1 < len(parts):
                    if (parts[i], parts[i + 1]) == (a, b):
                        parts[i : i + 2] = [a + b]
                    i += 1
            assert [tokens[i] for i in tool.encode_word(word.encode())] == parts, (merges, word)


def test_frames(spark, machine, library):
    rows = [(1, "Hello world", "x"), (None, None, "y"), (1, "Hello world", "x"), (3, "", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids string")
    made = bpe.encode(docs, machine)
    assert made.columns == ["doc_id", "text", "ids"]
    both = bpe.decode(made, machine).collect()
    assert sorted((r.decoded, tuple(r.ids)) for r in both) == sorted((t or "", tuple(library.encode(t or "", add_special_tokens=False).ids)) for _, t, _ in rows)
    assert bpe.encode(docs.limit(0), machine).count() == 0


def test_query(spark, library):
    from linform.llm.queries import op1_bpe, table

    d = "/root/testdata/sf0.001"
    got = {r.doc_id: r for r in op1_bpe(spark, d).collect()}
    docs = table(spark, d, "documents").collect()
    assert len(got) == len(docs)
    for r in docs:
        ids = library.encode(r.text or "", add_special_tokens=False).ids
        assert got[r.doc_id].n_tokens == len(ids)
        assert got[r.doc_id].ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[r.doc_id].decoded_sha256 == hashlib.sha256((r.text or "").encode()).hexdigest()


def test_a_worker_keeps_what_one_operator_knows(spark):
    """Caches of earlier stages would add up in the workers of a pipeline, and texts that are sent twice in their batches."""
    from linform.llm import common, quality

    first = common.held("a", lambda: [1])
    assert common.held("a", lambda: [2]) is first
    assert common.held("b", lambda: [3]) == [3] and list(common._HELD) == ["b"]
    docs = spark.createDataFrame([(1, "the of"), (2, None)], "doc_id long, text string")
    for df in (quality.score(docs, np.zeros((1 << quality.SPACE) + 1, np.float32)), bpe.encode(docs, bpe.MergeAutomaton({"a": 0}, []))):
        assert "_asked" not in df._jdf.queryExecution().optimizedPlan().toString()
