"""Secret scans weighed by how widely each value is held in the corpus.

A scan finds the base kinds (assign, access, hex) and, outside their spans, bare candidates: long mixed strings
with no telling context. Values leave the scan as hashes only. For each hash the corpus is then asked in how
many repositories and by how many owners it is held: values of many owners or many repositories are widely copied
examples (one owner may copy an example into thousands of repositories), values of one owner and few
repositories that look drawn at random are live-looking credentials. Bare candidates of the second sort are
added to the spans; base spans always stay, with counts of both sorts beside them.

Null texts count as empty; null repositories and owners each count as one. Repeated rows are scanned each, and
count once as repositories. An empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.llm.common import materialise, redealt, row_ids, texts_of

# The base patterns, in the order in which kinds are listed, with the least length of the value.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
KINDS = ("assign", "access", "hex", "owned")
BARE = re.compile(r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_=-]*[0-9])(?=[0-9+/_=A-Z-]*[a-z])(?=[0-9+/_=a-z-]*[A-Z])[A-Za-z0-9+/_=-]{20,}")
LONG_HEX = re.compile(r"[0-9a-f]{32,}")


def entropy(value: str) -> float:
    """Bits a character."""
    n = len(value)
    return -sum(c / n * math.log2(c / n) for c in Counter(value).values()) if n else 0.0


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """(start, kind number, end, value) of the base kinds, by start, then kind."""
    out = [(m.start(), 0, m.end(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end(), m[0]) for m in ACCESS.finditer(text) if len(m[0]) >= 16]
    out += [(m.start(), 2, m.end(), m[0]) for m in LONG_HEX.finditer(text)]  # the runs of HEX that are long enough
    return sorted(out)


def bare_spans(text: str, taken: list[tuple[int, int, int, str]], least_bits: float) -> list[tuple[int, int, int, str]]:
    """Mixed strings of 20 or more characters outside the taken spans."""
    found = [(m.start(), 3, m.end(), m[0]) for m in BARE.finditer(text)]
    return [x for x in found if entropy(x[3]) >= least_bits and not any(x[0] < t[2] and t[0] < x[2] for t in taken)]


def _joined(spans) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b, *_ in spans)


#: A value is narrowly held by at most so many owners and repositories: a credential may be in some files and copies of them.
MAX_OWNERS, MAX_REPOS = 1, 10

SPAN = "start int, kind int, end int, held binary, random boolean"


def scan(docs: DataFrame, repo_col: str, owner_col: str, text_col: str = "text", least_bits: float = 3.0) -> DataFrame:
    """(row, repo, owner, n_assign, n_access, n_hex, base_sha256, found) for every row; found: array of SPAN."""
    kind = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32()), ("held", pa.binary()), ("random", pa.bool_())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = 0
        for batch in batches:
            base_of, all_of = [], []
            for text in texts_of(batch.column(2)):
                base = base_spans(text)
                base_of.append(base)
                spans = base + bare_spans(text, base, least_bits)
                all_of.append([{"start": a, "kind": k, "end": b, "held": hashlib.sha256(v.encode()).digest()[:16], "random": entropy(v) >= least_bits} for a, k, b, v in spans])
            counts = [pa.array([sum(s[1] == k for s in base) for base in base_of], pa.int64()) for k in range(3)]
            digests = pa.array([hashlib.sha256(_joined(base).encode()).hexdigest() for base in base_of], pa.string())
            yield pa.RecordBatch.from_arrays(
                [row_ids(seen, batch.num_rows), batch.column(0), batch.column(1), *counts, digests, pa.array(all_of, kind)],
                names=["row", "repo", "owner", "n_assign", "n_access", "n_hex", "base_sha256", "found"],
            )
            seen += batch.num_rows

    asked = docs.select(F.col(repo_col).alias("repo"), F.col(owner_col).alias("owner"), F.col(text_col).cast("string").alias("text"))
    head = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in asked.schema.fields[:2])
    return asked.mapInArrow(run, f"row long, {head}, n_assign long, n_access long, n_hex long, base_sha256 string, found array<struct<start: int, kind: int, end: int, held: binary, random: boolean>>")


def ownership(scanned: DataFrame) -> DataFrame:
    """(held, n_repos, n_owners) of every candidate value: distinct counts in three steps, each combined before its shuffle."""
    held = scanned.select("repo", "owner", F.explode(F.array_distinct(F.transform("found", lambda x: x["held"]))).alias("held"))
    by_owner = held.groupBy("held", "owner", "repo").agg(F.lit(1).alias("one")).groupBy("held", "owner").agg(F.count("*").alias("repos"))
    return by_owner.groupBy("held").agg(F.sum("repos").alias("n_repos"), F.count("*").alias("n_owners"))


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", repo_col: str = "doc_id", owner_col: str = "source", text_col: str = "text", max_owners: int = MAX_OWNERS, least_bits: float = 3.0, max_repos: int = MAX_REPOS) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans, repos, owners, n_owned, n_live, n_example), one row for each row of docs.

    repos, owners: of each span, how many distinct repositories and owners hold its value. n_live, n_example: base
    spans whose value is held by at most max_owners and max_repos and looks random, or by more of either.
    """
    from_repo = docs.withColumn("_repo", F.struct(F.col(id_col).alias("id"), F.col(repo_col).alias("repo")))
    scanned = materialise(scan(from_repo, "_repo", owner_col, text_col, least_bits).withColumn("id", F.col("repo.id")).withColumn("repo", F.col("repo.repo")), "secrets")
    each = scanned.where(F.size("found") > 0).select("row", F.inline("found"))
    weighed = each.join(redealt(ownership(scanned), "held"), "held").withColumn("few", (F.col("n_owners") <= max_owners) & (F.col("n_repos") <= max_repos))
    told = (
        weighed.where((F.col("kind") < 3) | (F.col("few") & F.col("random")))
        .groupBy("row")
        .agg(
            F.array_sort(F.collect_list(F.struct("start", "kind", "end", "n_repos", "n_owners"))).alias("told"),
            F.sum((F.col("kind") == 3).cast("long")).alias("n_owned"),
            F.sum((F.col("few") & F.col("random") & (F.col("kind") < 3)).cast("long")).alias("n_live"),
            F.sum((~F.col("few") & (F.col("kind") < 3)).cast("long")).alias("n_example"),
        )
    )
    names = F.array(*map(F.lit, KINDS))
    text = F.array_join(F.transform("told", lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"], x["end"])), ",")
    out = scanned.drop("found").join(told, "row", "left")
    zero = [F.coalesce(c, F.lit(0).cast("long")).alias(c) for c in ("n_owned", "n_live", "n_example")]
    held = [F.coalesce(F.col(f"told.n_{c}"), F.array().cast("array<long>")).alias(c) for c in ("repos", "owners")]
    return out.select(F.col("id").alias("doc_id"), "n_assign", "n_access", "n_hex", "base_sha256", F.coalesce(text, F.lit("")).alias("spans"), *held, *zero)
