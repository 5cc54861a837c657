"""Exact duplicates through a cuckoo-filter index of live digests.

The text is lower-cased in A-Z only and digested (SHA-256); a content key is the digest and the length in bytes. Each
task keeps an index of the keys it has seen: a cuckoo filter of short marks (two candidate buckets a key), and beside
each bucket of marks a bucket of the keys and values that the marks stand for. Lookups ask the two buckets' marks;
only where one agrees is the key in that place read and verified, so a false hit costs a comparison and no wrong
answer. When a later row of a text wins, the entry it beats is deleted and its own inserted; when kicks run out, the
table is doubled and filled again from the stored keys. Tasks first index their own rows and hand the entries on when
they hold FLUSH of them, so a text that fills a third of the input leaves each task as a few rows; the index is then
built by digest, one independent part in each partition, with a number of partitions by which a part holds some PART
keys, however many there are.

Null texts count as empty. A null doc_id ranks below all others; of rows that repeat the winning doc_id with
an equal text, one stays. An empty table gives an empty result. Columns other than doc_id and text aren't read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.llm.common import materialise, row_ids, texts_of

SLOTS, KICKS = 4, 200
#: Entries that a task keeps before it hands them on; keys of one part of the index at most (some 400 bytes
#: each in a worker) and at least.
FLUSH, PART, LEAST = 100_000, 250_000, 10_000


class CuckooIndex:
    """Keys are bytes that begin with a digest (of 16 bytes at least); values are any objects. Answers are exact."""

    def __init__(self, buckets: int = 1024):
        self.size, self.live, self.resizes, self.false_hits = buckets, 0, 0, 0
        self._marks: list[list[int]] = [[] for _ in range(buckets)]
        self._held: list[list[tuple[bytes, object]]] = [[] for _ in range(buckets)]

    def _places(self, key: bytes) -> tuple[int, int, int]:
        mark = int.from_bytes(key[:2], "big") | 1 << 16
        first = int.from_bytes(key[2:10], "big") & self.size - 1
        return mark, first, self._other(first, mark)

    def _other(self, bucket: int, mark: int) -> int:
        return (bucket ^ mark * 0x5BD1E995) & self.size - 1

    def maybe(self, key: bytes) -> bool:
        """What the filter alone says: no means no."""
        mark, a, b = self._places(key)
        return mark in self._marks[a] or mark in self._marks[b]

    def _find(self, key: bytes) -> tuple[int, int]:
        """Bucket and slot of a live key; (-1, -1) if there is none."""
        mark, a, b = self._places(key)
        for bucket in (a, b) if a != b else (a,):
            if mark in self._marks[bucket]:
                for slot, other in enumerate(self._marks[bucket]):
                    if other == mark:
                        if self._held[bucket][slot][0] == key:
                            return bucket, slot
                        self.false_hits += 1
        return -1, -1

    def get(self, key: bytes):
        """The value of a live key, verified; None if there is none."""
        bucket, slot = self._find(key)
        return None if bucket < 0 else self._held[bucket][slot][1]

    def insert(self, key: bytes, value) -> None:
        if self._find(key)[0] >= 0:
            raise KeyError("the key is live; delete it first")
        self.live += 1
        over = (key, value) if self.live > 0.9 * SLOTS * self.size else self._place((key, value))
        if over is not None:
            self._grow(over)

    def delete(self, key: bytes) -> bool:
        bucket, slot = self._find(key)
        if bucket < 0:
            return False
        del self._marks[bucket][slot], self._held[bucket][slot]
        self.live -= 1
        return True

    def items(self):
        for bucket in self._held:
            yield from bucket

    def _place(self, entry: tuple[bytes, object]) -> tuple[bytes, object] | None:
        """Put an entry in one of its buckets, moving others on; returns the one that is left over when kicks run out."""
        mark, a, b = self._places(entry[0])
        bucket = a if len(self._marks[a]) < SLOTS else b
        for kick in range(KICKS):
            marks, held = self._marks[bucket], self._held[bucket]
            if len(marks) < SLOTS:
                marks.append(mark)
                held.append(entry)
                return None
            slot = (mark + kick) % SLOTS
            mark, marks[slot] = marks[slot], mark
            entry, held[slot] = held[slot], entry
            bucket = self._other(bucket, mark)
        return entry

    def _grow(self, over: tuple[bytes, object]) -> None:
        """Double until every stored key has a place."""
        entries, left = [*self.items(), over], over
        while left is not None:
            self.size *= 2
            self.resizes += 1
            self._marks, self._held = [[] for _ in range(self.size)], [[] for _ in range(self.size)]
            left = next((x for x in map(self._place, entries) if x is not None), None)


def content_key(text: str) -> bytes:
    """SHA-256 of the text in lower case (A-Z only), and its length in bytes."""
    content = text.encode("utf-8", "surrogatepass").lower()
    return hashlib.sha256(content).digest() + len(content).to_bytes(8, "big")


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row, doc_id, digest) for every row; digest: the content key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = 0
        for batch in batches:
            made = [content_key(x) for x in texts_of(batch.column(1))]
            yield pa.RecordBatch.from_arrays([row_ids(seen, len(made)), batch.column(0), pa.array(made, pa.binary())], names=["row", "doc_id", "digest"])
            seen += len(made)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "row long, doc_id long, digest binary")


def _indexed(rows: DataFrame, flush: int | None = None) -> DataFrame:
    """(digest, doc_id, row, n) -> one row a digest in each partition (each time the index is handed on, if it is when
    it holds `flush` entries): the winning row and the sum of n."""

    def told(index: CuckooIndex) -> Iterator[pa.RecordBatch]:
        kept = [(k, v[1], v[2], v[3]) for k, v in index.items()]
        for at in range(0, len(kept), 10_000):
            part = [*zip(*kept[at : at + 10_000], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(part[0], pa.binary()), *(pa.array(c, pa.int64()) for c in part[1:])], names=["digest", "doc_id", "row", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = CuckooIndex()
        for batch in batches:
            for digest, doc_id, row, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                rank = (doc_id is not None, doc_id or 0, row)
                live = index.get(digest)
                if live is None:
                    index.insert(digest, [rank, doc_id, row, n])
                elif rank > live[0]:
                    index.delete(digest)
                    index.insert(digest, [rank, doc_id, row, n + live[3]])
                else:
                    live[3] += n
                if flush and index.live >= flush:
                    yield from told(index)
                    index = CuckooIndex()
        yield from told(index)

    return rows.mapInArrow(run, "digest binary, doc_id long, row long, n long")


def _by_digest(parts: DataFrame, part: int) -> DataFrame:
    """Entries of one digest together, in partitions of some `part` keys; as many as can run at once, if each gets LEAST."""
    held = materialise(parts, "digest-entries")
    n, cores = held.count(), held.sparkSession.sparkContext.defaultParallelism
    return _indexed(held.repartition(max(-(-n // part), min(cores, n // LEAST), 1), "digest"))


def build_index(digested: DataFrame, flush: int = FLUSH, part: int = PART) -> DataFrame:
    """(row, doc_id, digest) -> (digest, keep_id, keep_row, group_size), one row a live digest."""
    own = _indexed(digested.select("digest", "doc_id", "row", F.lit(1).cast("long").alias("n")), flush)
    return _by_digest(own, part).select("digest", F.col("doc_id").alias("keep_id"), F.col("row").alias("keep_row"), F.col("n").alias("group_size"))


def apply_changes(index: DataFrame, inserts: DataFrame, deletes: DataFrame) -> DataFrame:
    """An index (as build_index gives it) after deletes of (digest) and then inserts of (row, doc_id, digest)."""
    left = index.join(deletes.select("digest").distinct(), "digest", "left_anti")
    held = left.select("digest", F.col("keep_id").alias("doc_id"), F.col("keep_row").alias("row"), F.col("group_size").alias("n"))
    new = _indexed(inserts.select("digest", "doc_id", "row", F.lit(1).cast("long").alias("n")), FLUSH)
    return _by_digest(held.unionByName(new), PART).select("digest", F.col("doc_id").alias("keep_id"), F.col("row").alias("keep_row"), F.col("n").alias("group_size"))


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256), one row for each row of docs."""
    rows = materialise(digests(docs, id_col, text_col), "digests")
    index = build_index(rows)
    return rows.join(index, "digest").select("doc_id", "keep_id", "group_size", (F.col("row") == F.col("keep_row")).alias("kept"), F.lower(F.hex(F.substring("digest", 1, 32))).alias("text_sha256"))
