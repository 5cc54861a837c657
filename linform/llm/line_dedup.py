"""Line dedup over a suffix array of line ids, in DataFrame functions only.

Lines (blank ones aside; blank: white space only) are numbered in their document and named by two hashes of their
text. Lines that occur once break runs and are left out at once. Suffixes are then ranked by prefix doubling: the
rank at level k orders runs of 2**k lines, and a level ranks pairs of a rank and that of the run that follows.
Distinct pairs are counted before anything is dealt, dealt by range of the pair, sorted, and numbered in that order,
so ranks ascend as the pairs do; no window and no task holds the successors of one line, and a line that fills a
third of the table weighs as its distinct successors only, over as many ranges as they need. Runs that occur once
leave a level: their place in the suffix array is settled.

A repeated run matters once it holds `min_words` words. From each line (and up to each line) the least run that
long is taken; the suffixes that share it as a prefix are an interval of the suffix array whose longest common
prefix is at least that, named by the ranks of the two runs of 2**k lines that cover it. All positions of an
interval but the first are later copies, and the runs over them overlap to the maximal repeated runs: a line is
deleted if some run around it, of min_words words or more, occurred before. Intervals of longer prefixes lie inside
these and delete nothing more, so levels beyond min_words lines are never needed, however long the copies are.

Order of occurrence: doc_id (null last), text hash, line. Null texts count as empty. Rows that repeat id and
text are one document in that order; each gets the same result. Lines are equal if all their characters are, a
carriage return at the end included; words are what white space of any kind parts. An empty table gives an empty
result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linform.llm.common import materialise, redealt

MIN_WORDS = 20
KEY = ["kid", "dk"]
# Fixed value: a character that is no white space, and all white space that parts words.
_SOLID, _SPACE = r"[^\s\x1c-\x1f\x85\p{Z}]", r"[\s\x1c-\x1f\x85\p{Z}]+"


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with (kid, dk), its key in the order of occurrence, and the lines that are not blank with their places."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.withColumn("kid", F.coalesce(F.col(id_col).cast("long"), F.lit(2**63 - 1))).withColumn("dk", F.xxhash64(F.col(id_col).isNull(), text)).withColumn("_text", text)


def lines_of(text: Column) -> Column:
    """The lines that are not blank: (at: number among all lines, line)."""
    numbered = F.transform(F.split(text, "\n"), lambda x, i: F.struct(i.alias("at"), x.alias("line")))
    return F.filter(numbered, lambda x: is_solid(x["line"]))


def is_solid(text: Column | str) -> Column:
    """Whether a text holds anything but white space."""
    return (F.col(text) if isinstance(text, str) else text).rlike(_SOLID)


def words_in(line: Column) -> Column:
    """How many words a line holds."""
    return F.size(F.filter(F.split(line, _SPACE), lambda w: w != ""))


def repeated_lines(texts: DataFrame) -> DataFrame:
    """(kid, dk, _text) -> (kid, dk, pos, at, l0, l1, words) of lines that occur more than once."""
    lines = texts.select(*KEY, F.posexplode(lines_of(F.col("_text"))).alias("pos", "x"))
    line = F.col("x.line")
    lines = lines.select(*KEY, "pos", "x.at", F.xxhash64(line).alias("l0"), F.xxhash64(F.lit(1), line).alias("l1"), words_in(line).alias("words"))
    counts = lines.groupBy("l0", "l1").agg(F.count("*").alias("n")).where("n > 1")
    own = materialise(lines.join(redealt(counts, "l0"), ["l0", "l1"]).drop("n").dropDuplicates([*KEY, "pos"]), "lines")  # rows that repeat are one document
    again = own.groupBy("l0", "l1").agg(F.count("*").alias("n")).where("n > 1")
    return own.join(redealt(again, "l0"), ["l0", "l1"]).drop("n")


def ranked(counted: DataFrame, names: list[str]) -> DataFrame:
    """Distinct names with r, which ascends as they do: the number of the range in its high bits, the place in the
    sorted range in its low ones."""
    return materialise(counted.repartitionByRange(*names).sortWithinPartitions(*names).select(*names, F.monotonically_increasing_id().alias("r")), "line-order")


def doubled(level: DataFrame, reach: int) -> DataFrame:
    """Ranks of runs of `reach` lines -> ranks of runs of twice as many, of those that occur more than once."""
    after = level.select(*KEY, (F.col("pos") - reach).alias("pos"), F.col("r").alias("s"))
    pairs = materialise(level.join(after, [*KEY, "pos"]).withColumnRenamed("r", "p"), "line-pairs")
    again = pairs.groupBy("p", "s").agg(F.count("*").alias("n")).where("n > 1").drop("n")
    return pairs.join(redealt(ranked(again, ["p", "s"]), "p"), ["p", "s"]).select(*KEY, "pos", "r")


def suffix_levels(lines: DataFrame, depth: int) -> list[DataFrame]:
    """Rank tables of levels 0, 1, ...: (kid, dk, pos, r), as long as runs repeat and are within depth lines."""
    order = ranked(lines.groupBy("l0", "l1").agg(F.lit(1).alias("one")).drop("one"), ["l0", "l1"])
    level = materialise(lines.join(redealt(order, "l0"), ["l0", "l1"]).select(*KEY, "pos", "r"), "line-ranks")
    levels = [level]
    while 1 << len(levels) <= depth:
        level = materialise(doubled(level, 1 << len(levels) - 1), "line-ranks")
        if level.isEmpty():
            break
        levels.append(level)
    return levels


def least_runs(lines: DataFrame, min_words: int) -> DataFrame:
    """(kid, dk, start, m): the least runs of min_words words from each line and up to each line, of adjoining repeated lines."""
    doc = Window.partitionBy(*KEY)
    told = lines.select(*KEY, "pos", "words").withColumn("upto", F.sum("words").over(doc.orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)))
    told = told.withColumn("since", F.col("upto") - F.col("words"))
    ahead, back = doc.orderBy("since").rangeBetween(0, min_words - 1), doc.orderBy("upto").rangeBetween(-(min_words - 1), 0)
    ends = told.withColumns(
        {
            "n": F.count("*").over(ahead), "last": F.max("pos").over(ahead), "held": F.max("upto").over(ahead) - F.col("since"),
            "b_n": F.count("*").over(back), "b_first": F.min("pos").over(back), "b_held": F.col("upto") - F.min("since").over(back),
        }
    )
    forth = ends.where((F.col("last") - F.col("pos") + 1 == F.col("n")) & (F.col("held") >= min_words)).select(*KEY, F.col("pos").alias("start"), F.col("n").alias("m"))
    up = ends.where((F.col("pos") - F.col("b_first") + 1 == F.col("b_n")) & (F.col("b_held") >= min_words)).select(*KEY, F.col("b_first").alias("start"), F.col("b_n").alias("m"))
    return forth.union(up).distinct()


def later_copies(levels: list[DataFrame], runs: DataFrame) -> DataFrame:
    """Of the runs (kid, dk, start, m), those that occurred before."""
    ranks = levels[0].withColumn("k", F.lit(0))
    for k, level in enumerate(levels[1:], 1):
        ranks = ranks.unionByName(level.withColumn("k", F.lit(k)))
    head = ranks.select(*KEY, "k", F.col("pos").alias("start"), "r")
    tail = ranks.select(*KEY, "k", F.col("pos").alias("tail"), F.col("r").alias("s"))
    runs = runs.withColumn("k", F.floor(F.log2("m")).cast("int")).withColumn("tail", (F.col("start") + F.col("m") - F.expr("shiftleft(1, k)")).cast("int"))
    named = materialise(runs.join(head, [*KEY, "k", "start"]).join(tail, [*KEY, "k", "tail"]).drop("tail", "k"), "line-runs")
    name, place = ["m", "r", "s"], F.struct("kid", "dk", "start")
    interval = named.groupBy(*name).agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    return named.join(redealt(interval, "r"), name).where(F.col("first") < place).select(*KEY, "start", "m")


def repeated_runs(lines: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(kid, dk, pos, at, run) of the lines in later copies of repeated runs; lines of one maximal run share `run`."""
    copies = later_copies(suffix_levels(lines, min_words), least_runs(lines, min_words))
    reach_of = copies.groupBy(*KEY, F.col("start").alias("pos")).agg(F.max(F.col("start") + F.col("m")).alias("end"))
    line = Window.partitionBy(*KEY).orderBy("pos")
    each = lines.select(*KEY, "pos", "at").join(reach_of, [*KEY, "pos"], "left")
    each = each.withColumn("before", F.max("end").over(line.rowsBetween(Window.unboundedPreceding, -1)))
    each = each.withColumn("begins", (F.col("end").isNotNull() & (F.coalesce("before", F.lit(-1)) <= F.col("pos"))).cast("int"))
    each = each.withColumn("run", F.sum("begins").over(line))
    return each.where(F.greatest(F.coalesce("before", F.lit(-1)), F.coalesce("end", F.lit(-1))) > F.col("pos")).select(*KEY, "pos", "at", "run")


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """All columns of docs with later copies of repeated line runs deleted from the text, and n_lines, n_deleted.

    Texts from which nothing is deleted stay as they are (null stays null). Columns of docs named n_lines,
    n_deleted, kid, dk, gone or _text are replaced or dropped.
    """
    kept = [c for c in docs.columns if c not in ("n_lines", "n_deleted", "kid", "dk", "_text", "gone")]
    texts = keyed(docs.select(*kept), id_col, text_col)
    lines = materialise(repeated_lines(texts.select(*KEY, "_text")), "lines")
    gone = repeated_runs(lines, min_words).groupBy(*KEY).agg(F.collect_list("at").alias("gone"))
    both = texts.join(gone, KEY, "left")
    split = F.split("_text", "\n")
    left = F.array_except(F.sequence(F.lit(0), F.size(split) - 1), F.col("gone"))
    text = F.when(F.col("gone").isNull(), F.col(text_col)).otherwise(F.array_join(F.flatten(F.transform(F.array(split), lambda all_of: F.transform(left, lambda i: F.get(all_of, i)))), "\n"))
    out = [text.alias(c) if c == text_col else F.col(c) for c in kept]
    return both.select(*out, F.size(split).alias("n_lines"), F.when(F.col("gone").isNull(), 0).otherwise(F.size("gone")).alias("n_deleted"))
