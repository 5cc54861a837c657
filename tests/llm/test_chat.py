import hashlib
import random

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from linform.llm import chat as C


@settings(max_examples=300, deadline=None)
@given(st.text("<|\\/im_startend>\n a"), st.text("<|\\imn>\n "))
def test_escapes(text, role):
    written, a, b = C.render(role, text)
    assert C.unescape(C.escape(text)) == text
    assert C.read_turns(written * 2) == [(role, text)] * 2
    assert (C.unescape(written[a:b]) == text) if role == "assistant" else a == b


def want(turns):
    turns = [(r or "", t or "") for r, t in turns]
    loss = "".join(t for r, t in turns if r == "assistant")
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    return len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss)


def test_rows(spark):
    rng = random.Random(8)
    convs = {}
    for c in range(40):
        convs[c] = [(rng.choice(["user", "assistant", "system", None, "a\nb\\"]), rng.choice([None, "", "x", "é🙂" * 3000, "<|im_end|>", "a<\\|b", "y\n" * 5])) for _ in range(rng.randrange(1, 7))]
    convs[None] = [("assistant", "lost")]
    convs[50] = [("user", f"t{i:05d}") for i in range(3000)]
    rows = [(c, i, r, t, "q") for c, x in convs.items() for i, (r, t) in enumerate(x)]
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, part string").repartition(4)
    got = C.digest(C.fold(C.events_of(df))).collect()
    assert {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in got} == {c: want(x) for c, x in convs.items()}
    assert len(got) == len(convs)
    assert C.digest(C.fold(C.events_of(df.limit(0)))).count() == 0
    tied = spark.createDataFrame([(1, 0, "user", "b" * 5000), (1, 0, "user", "b" * 5000), (1, None, "user", "n"), (1, 0, "user", "a")], "conv_id long, turn long, role string, text string")
    assert [r.n_turns for r in C.digest(C.fold(C.events_of(tied))).collect()] == [4]


def test_history_is_in_the_log_and_leaves_no_trace(spark):
    rows = [(c, t, "user" if t % 2 == 0 else "assistant", f"text {c} {t} " * (1 + 700 * (c % 9 == 0))) for c in range(60) for t in range(4)]
    rows += [(7, 1, "assistant", "a tied turn"), (7, 1, "assistant", "a tied turn"), (8, None, "user", None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(4)
    log = C.events_of(df)
    kinds = {r.kind: r.n for r in log.groupBy("kind").agg(F.count("*").alias("n")).collect()}
    assert kinds["edit"] > 20 and kinds["regenerate"] > 20
    kept = C.live_events(log, [*C.NAMES, "part"], C.NAMES)
    assert kept.where("kind = 'regenerate' or text like 'draft%'").count() == 0 < log.where("text like 'draft%'").count()
    out = lambda x: sorted(map(str, C.digest(C.fold(x)).collect()))
    assert out(log) == out(C.events_of(df, history=0))
    assert {r.kind for r in C.events_of(df, history=0).select("kind").distinct().collect()} == {"start", "delta"}


def slow_fold(events):
    messages = {}
    for _, m, kind, role, text in sorted(events):
        if kind == "start":
            messages[m] = [role, text]
        elif kind == "regenerate":
            messages = {k: v for k, v in messages.items() if k < m}
        elif m in messages:
            messages[m][1] = text if kind == "edit" else messages[m][1] + text
    return [tuple(messages[m]) for m in sorted(messages)]


def test_streamed_edits_and_regenerations(spark):
    rng, logs = random.Random(4), {}
    for c in range(60):
        log, seq, top = [], 0, 0
        while top < rng.randrange(1, 6) or not log:
            log.append((seq, top, "start", rng.choice(["user", "assistant"]), ""))
            seq += 1
            if rng.random() < 0.2:
                log += [(seq, top, "delta", None, "gone"), (seq + 1, top, "edit", None, "too"), (seq + 2, top, "start", "assistant", "again")]
                seq += 3
            for _ in range(rng.randrange(4)):
                kind = rng.choice(["delta", "delta", "edit"])
                m = top if kind == "delta" else rng.randrange(top + 1)
                log.append((seq, m, kind, None, f"{seq},"))
                seq += 1
            top += 1
            if rng.random() < 0.3:
                top = rng.randrange(top)
                log.append((seq, top, "regenerate", None, None))
                seq += 1
                if rng.random() < 0.3:
                    break
        logs[c] = log
    rows = [(c, s, m, k, r, t) for c, log in logs.items() for s, m, k, r, t in log]
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "conv_id long, seq long, message long, kind string, role string, text string").repartition(4)
    got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in C.digest(C.fold(df, ["seq"])).collect()}
    assert got == {c: want(slow_fold(log)) for c, log in logs.items() if slow_fold(log)}
