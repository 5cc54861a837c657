"""Document fingerprints: threshold-scaled sketches of word shingles, in DataFrame functions only.

The sketch of a text is the set of hashes of its five-word shingles (of the whole text where it has fewer words)
that lie below one fixed fraction of the hash range, the same for texts of every length, and the least hash of all,
whatever it is. So sketches of unequal texts are comparable as they are, and merge: the sketch of two shingle sets'
union is what `merged` makes of their sketches.

Likeness is the share of common hashes among all those of two sketches below the fraction; its standard error is
sqrt(j (1 - j) (1 - f) / (f n)) for likeness j, fraction f and n distinct shingles in both texts together (at f = 1/4
and j = 1/2: 0.27 at 10 shingles, 0.09 at 100, 0.03 at 1,000). Where neither has a hash below the fraction, it is 1 if
their least hashes are equal and 0 if not, which is right in the mean; two sketches of no shingles at all are alike (1),
none and another are not (0). Containment is the share of a's hashes below the fraction that b has: 1 for a text
without shingles, null (unknown) where a has shingles but none below the fraction.

Null texts count as empty; a text without words has an empty sketch. Documents are ordered by (doc_id, text hash),
null ids first; rows that repeat both are one document in that order, and each gets the same result. An empty table
gives an empty result. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linform.llm.common import materialise

SHINGLE, FRACTION = 5, 1 / 4


def below(fraction: float):
    """Whether a hash, as an unsigned number, lies below the fraction of the range."""
    return lambda h: F.shiftrightunsigned(h, 1) < F.lit(min(int(fraction * 2**63), 2**63 - 1)).cast("long")


def shingle_hashes(text: Column, shingle: int = SHINGLE) -> Column:
    """Hashes of the shingles, repeats included."""
    words = F.filter(F.split(text, r"\s+"), lambda w: w != "")
    hashed = F.transform(words, lambda w: F.xxhash64(w))

    def runs(all_of: Column) -> Column:
        starts = F.slice(all_of, 1, F.greatest(F.size(all_of) - (shingle - 1), F.lit(1)))
        return F.transform(starts, lambda h, i: F.xxhash64(h, *(F.get(all_of, i + k) for k in range(1, shingle))))

    # a one-element array binds the word hashes, so that they are made once
    return F.flatten(F.transform(F.array(hashed), runs))


def with_sketch(df: DataFrame, text_col: str, name: str, fraction: float = FRACTION) -> DataFrame:
    """df and a column <name>: the sorted distinct hashes below the fraction, and the least of all, by unsigned size."""
    hashes = F.array_distinct(shingle_hashes(F.coalesce(F.col(text_col), F.lit(""))))
    made = df.withColumn("_h", hashes)
    return made.withColumn(name, _kept(F.col("_h"), fraction)).drop("_h")


def _ascending(h: Column) -> Column:
    """Hashes as numbers whose signed order is the unsigned one of the hashes; its own inverse."""
    return h.bitwiseXOR(F.lit(-(2**63)).cast("long"))


def _kept(hashes: Column, fraction: float) -> Column:
    low = F.filter(hashes, below(fraction))
    # a one-element array binds the filtered hashes, so that they are made once
    least = F.transform(F.slice(F.array_sort(F.transform(hashes, _ascending)), 1, 1), _ascending)
    kept = F.transform(F.array(low), lambda x: F.when(F.size(x) > 0, F.transform(F.array_sort(F.transform(x, _ascending)), _ascending)).otherwise(least))
    return F.get(kept, 0)


def merged(a: Column, b: Column, fraction: float = FRACTION) -> Column:
    """The sketch of the union of two shingle sets, from their sketches."""
    return _kept(F.array_union(a, b), fraction)


def with_likeness(df: DataFrame, a: str, b: str, likeness: str, containment: str | None = None, fraction: float = FRACTION) -> DataFrame:
    """df and the share of common hashes among those of sketches a and b, and among those of a."""
    df = df.withColumn("_a", F.filter(a, below(fraction))).withColumn("_b", F.filter(b, below(fraction)))
    df = df.withColumn("_n", F.size(F.array_intersect("_a", "_b")).cast("double"))
    union = F.size("_a") + F.size("_b") - F.col("_n")
    df = df.withColumn(likeness, F.when(union > 0, F.col("_n") / union).otherwise((F.col(a) == F.col(b)).cast("double")))
    if containment:
        shared = F.when(F.size("_a") > 0, F.col("_n") / F.size("_a"))
        df = df.withColumn(containment, F.when(F.size(a) == 0, F.lit(1.0)).otherwise(shared))
    return df.drop("_a", "_b", "_n")


def as_text(sketch: str, fraction: float = FRACTION) -> Column:
    hexes = F.transform(F.col(sketch), lambda h: F.lpad(F.lower(F.hex(h)), 16, "0"))
    return F.concat(F.lit(f"{fraction:g}:"), F.array_join(hexes, ""))


def following(keys: DataFrame) -> DataFrame:
    """(kid, dk, n) without repeats -> (kid, dk, before_kid, before_dk, before_n): the key whose next one each is.

    Keys are dealt by range, and windows stay inside a range; only the ends of ranges, one row a partition, meet
    in one place. The first key follows the last.
    """
    ranged = materialise(keys.repartitionByRange("kid", "dk").withColumn("pid", F.spark_partition_id()), "order")
    ends = ranged.groupBy("pid").agg(F.max(F.struct("kid", "dk", "n")).alias("end"))
    line = Window.orderBy("pid")  # as many rows as ranges
    whole = line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ends = ends.select("pid", F.coalesce(F.lag("end").over(line), F.last("end").over(whole)).alias("end"))
    own = Window.partitionBy("pid").orderBy("kid", "dk")
    got = ranged.withColumn("before", F.lag(F.struct("kid", "dk", "n")).over(own)).join(ends, "pid")
    got = got.withColumn("before", F.coalesce("before", "end"))
    return got.select("kid", "dk", F.col("before.kid").alias("before_kid"), F.col("before.dk").alias("before_dk"), F.col("before.n").alias("before_n"))


def edited_and_next(docs: DataFrame, fraction: float = FRACTION) -> DataFrame:
    """Each document beside its edited text (second half from the next document) and the next document.

    Returns doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next,
    contained_edited (share of the document's hashes that the edited text has; null: unknown), next_doc_id. Texts are dealt once
    by key (both joins ask for the same columns, so they share that exchange); beside that only the half that the
    document before needs travels, with the text's sketch.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    docs = docs.withColumn("kid", F.coalesce("doc_id", F.lit(-(2**63)))).withColumn("dk", F.xxhash64(F.col("doc_id").isNull(), "text"))
    order = materialise(following(docs.select("kid", "dk", F.length("text").alias("n")).distinct()), "following")
    supply = docs.join(order, ["kid", "dk"])
    first = F.row_number().over(Window.partitionBy("kid", "dk").orderBy(F.lit(0)))  # of rows that repeat a key
    supply = supply.withColumn("nth", first).where("nth = 1")
    supply = with_sketch(supply, "text", "c", fraction)
    supply = supply.select(F.col("before_kid").alias("kid"), F.col("before_dk").alias("dk"), F.expr("substring(text, 1, cast(before_n div 2 as int))").alias("head"), F.col("doc_id").alias("next_doc_id"), "c")
    main = docs.join(supply, ["kid", "dk"]).withColumn("n_chars", F.length("text").cast("long"))
    main = main.withColumn("edited", F.concat(F.expr("substring(text, 1, cast(n_chars - n_chars div 2 as int))"), "head"))
    main = with_sketch(with_sketch(main, "text", "a", fraction), "edited", "b", fraction)
    main = with_likeness(with_likeness(main, "a", "b", "near_edited", "contained_edited", fraction), "a", "c", "near_next", None, fraction)
    return main.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), as_text("a", fraction).alias("fingerprint"), as_text("b", fraction).alias("edited_fingerprint"), "near_edited", "near_next", "contained_edited", "next_doc_id")
