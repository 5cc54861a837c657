import random

import numpy as np

from linform.llm import quality as Q


def test_planted_signal_and_edge_cases(spark):
    rng = random.Random(1)
    good, bad = [f"g{i}" for i in range(80)], [f"b{i}" for i in range(80)]
    rows, labels = [], []
    for i in range(600):
        y = int(rng.random() < 0.6)
        words = rng.choices(good if y else bad, k=30) + rng.choices(good + bad, k=20)
        rng.shuffle(words)
        rows.append((i, " ".join(words), "z"))
        labels.append((i, y, 0))
    rows += [(9001, None, "z"), (9002, "", "z"), (None, "g1 g2", "z"), (9003, "g3 " * 200_000, "z"), (5, rows[5][1], "z")]
    labels += [(9001, None, 0), (None, 1, 0), (77777, 1, 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string").repartition(3)
    known = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = Q.classify(docs, known).collect()
    assert len(got) == len(rows)
    truth = {i: y for i, y, _ in labels}
    out = [(r.predicted, truth[r.doc_id]) for r in got if r.held_out and r.doc_id is not None and r.doc_id < 600]
    assert len(out) > 80 and np.mean([a == b for a, b in out]) > 0.9
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in got)
    import zlib

    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got if r.doc_id is not None)
    assert len({r.score for r in got if r.doc_id in (9001, 9002)}) == 1
    assert Q.classify(docs.limit(0), known).count() == 0
    assert {r.score for r in Q.classify(docs.limit(3), known.limit(0)).collect()} == {0.5}


def test_held_out_labels_change_nothing(spark):
    docs = spark.createDataFrame([(i, f"w{i % 7} w{i % 3}") for i in range(200)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, quality int")
    from pyspark.sql import functions as F

    flipped = labels.withColumn("quality", F.when(Q.held_out(), 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = (Q.train(docs, Q.known_labels(x, "quality")) for x in (labels, flipped))
    assert np.array_equal(a, b) and np.abs(a).sum() > 0


def test_query_on_held_out_rows(spark):
    from linform.llm.queries import op7_quality, table

    d = "/root/testdata/sf0.1"
    rows = op7_quality(spark, d).join(table(spark, d, "labels"), "doc_id").where("held_out").collect()
    right = np.mean([r.predicted == r.quality for r in rows])
    kept = np.mean([r.predicted for r in rows if r.quality == 1])
    dropped = np.mean([1 - r.predicted for r in rows if r.quality == 0])
    print(len(rows), right, kept, dropped)
    assert right > 0.9 and kept > 0.97 and dropped > 0.6
