"""Byte-pair encoding by a deterministic automaton compiled from the merge list, and decoding by arc labels.

The automaton reads tokens. It starts as one state with a loop for each byte; the merges are then applied in
rank order, each by a small gadget for (u, v) -> w:

* the arcs labelled u are redirected to a copy of their target that has no arc for v;
* the arc w is added beside every arc u, and leads where v led before the change.

All arcs with one label lead to one state, so the machine is: a state for each token, a tree of states (each a
copy of its parent less one arc), and for each token the merge that made it. delta(state, token) is then
answered by walking that tree, and answers are kept in a transition table that fills as it is used. A path
through the machine spells the only token sequence that the merges give for its bytes; encoding follows it arc
by arc, and decoding emits the labels of the arcs.

Null texts count as empty: no ids, empty decoded text. A string of a special token inside a text becomes that
token's id, as in the public library (where two begin at one place, the longer). Ids outside the vocabulary are dropped
on decoding, null lists count as empty. Rows are encoded each on its own, so rows that repeat or tie give equal results
and stay; an empty table gives an empty result. Columns of the same names as those added are replaced. Texts of any
length are encoded whole; words of any length are, too, without being kept.
"""

from __future__ import annotations

import json
import re
from itertools import chain

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.llm.common import asked_of, held

# Fixed value: the pre-split pattern of byte-level BPE.
PRE_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Words whose ids a worker keeps in each of two generations, answers kept in the transition table, rows in a batch out.
KEPT_WORDS, KEPT_ARCS, ROWS = 300_000, 1_000_000, 256


# The same cuts of ASCII texts for the standard library's engine, which is faster; it takes 1C to 1F for white space.
_QUICK = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[a-zA-Z]+| ?[0-9]+| ?[^\sa-zA-Z0-9]+|\s+(?!\S)|\s+")
_SEPARATORS = re.compile("[\x1c-\x1f]")


def byte_alphabet() -> dict[str, int]:
    """Printable stand-in for each byte, as byte-level vocabularies write them."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class WordIds(dict):
    """Ids of words, made when first asked for; keeps the present and the last generation of words."""

    def __init__(self, encode_word):
        super().__init__()
        self.encode_word, self.older = encode_word, {}

    def __missing__(self, word: str) -> tuple[int, ...]:
        found = self.older.get(word)
        if found is None:
            found = self.encode_word(word.encode())
        if len(word) <= 64:
            if len(self) >= KEPT_WORDS:
                self.older = dict(self)
                self.clear()
            self[word] = found
        return found


class LongestStart(dict):
    """For up to four bytes: the longest token that they begin with, or minus the node where longer ones go on."""

    def __init__(self, machine: MergeAutomaton):
        super().__init__()
        self.machine = machine

    def __missing__(self, part: bytes) -> int:
        node, t = 0, -1
        for byte in part:
            node = self.machine.trie.get(node << 8 | byte, -1)
            if node < 0:
                break
            t = self.machine.best[node]
        found = -node if node > 0 and len(part) == 4 else t
        if len(self) >= KEPT_WORDS:
            self.clear()
        self[part] = found
        return found


class MergeAutomaton:
    """Compiled once on the driver and broadcast; its size depends on the vocabulary only."""

    def __init__(self, vocab: dict[str, int], merges: list[tuple[str, str]], special: dict[str, int] | None = None):
        alphabet = byte_alphabet()
        self.special = dict(special or {})
        self.label = {i: bytes(alphabet[c] for c in t) for t, i in vocab.items() if all(c in alphabet for c in t)}
        self.label |= {i: t.encode() for t, i in self.special.items()}
        n = max(self.label, default=-1) + 1
        self.left, self.born, self.state = [-1] * n, [-1] * n, [0] * n
        self.parent, self.removed, self.made = [-1], [-1], [-1]  # of each state; state 0 has every arc
        self.arcs: dict[int, bool] = {}
        made_by_merges = {vocab[c] for c in alphabet if c in vocab}
        for rank, (a, b) in enumerate(merges):
            u, v, w = vocab[a], vocab[b], vocab[a + b]
            if u not in made_by_merges or v not in made_by_merges or not self.allows(self.state[u], v):  # earlier merges never leave this pair side by side
                continue
            after_v = self.state[v]
            self.parent.append(self.state[u])
            self.removed.append(v)
            self.made.append(rank)
            self.state[u] = len(self.parent) - 1
            self.left[w], self.born[w], self.state[w] = u, rank, after_v
            made_by_merges.add(w)
        self.trie: dict[int, int] = {}
        self.ends = [-1]
        for t in made_by_merges:
            node = 0
            for byte in self.label[t]:
                node = self.trie.setdefault(node << 8 | byte, len(self.ends))
                if node == len(self.ends):
                    self.ends.append(-1)
            self.ends[node] = t
        self.best = [-1] * len(self.ends)  # longest token on the way to each node
        for key, node in sorted(self.trie.items(), key=lambda x: x[1]):
            self.best[node] = self.ends[node] if self.ends[node] >= 0 else self.best[key >> 8]
        self.size = [len(self.label.get(t, b"")) for t in range(n)]
        self.shorter = [-1] * n  # the longest token that is a true prefix of each
        for t in made_by_merges:
            node = 0
            for byte in self.label[t][:-1]:
                node = self.trie[node << 8 | byte]
                if self.ends[node] >= 0:
                    self.shorter[t] = self.ends[node]
        self._fresh()

    @classmethod
    def from_file(cls, path: str) -> MergeAutomaton:
        """From a tokenizers JSON file with a byte-level BPE model."""
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        return cls(spec["model"]["vocab"], merges, {t["content"]: t["id"] for t in spec["added_tokens"]})

    def _fresh(self) -> None:
        self.arcs: dict[int, bool] = {}
        self.words = WordIds(self.encode_word)
        self.starts = LongestStart(self)
        self.spelling = [self.label.get(i, b"") for i in range(len(self.size))]
        self._split = regex.compile(PRE_SPLIT)
        cut = "|".join(regex.escape(t) for t in sorted(self.special, key=len, reverse=True))
        self._cut = regex.compile(f"({cut})") if cut else None

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("arcs", "words", "starts", "spelling", "_split", "_cut")}

    def __setstate__(self, kept: dict) -> None:
        self.__dict__.update(kept)
        self._fresh()

    def allows(self, state: int, token: int) -> bool:
        """Whether the state has an arc for the token."""
        key = state << 32 | token
        known = self.arcs.get(key)
        if known is None:
            s, t = state, token
            while s and t != self.removed[s]:
                if self.born[t] >= self.made[s]:  # the arc came after the state: beside the arc of its left part
                    t = self.left[t]
                else:  # the state was copied with the arcs of its parent
                    s = self.parent[s]
            known = s == 0
            if len(self.arcs) >= KEPT_ARCS:
                self.arcs.clear()
            self.arcs[key] = known
        return known

    def encode_word(self, word: bytes) -> tuple[int, ...]:
        """The one path that spells the word: depth first, longest arcs first.

        A prefix has one path only, so a position that fails once fails for good; time is in proportion to the
        length of the word (times the length of the longest token).
        """
        trie, ends, state, shorter, arcs, allows = self.trie, self.ends, self.state, self.shorter, self.arcs, self.allows
        size, n, at, s, dead, starts = self.size, len(word), 0, 0, set(), self.starts
        path: list[int] = []
        while at < n:
            t = starts[word[at : at + 4]]
            if t < 0:  # tokens of more bytes begin like this: go on from their node
                node, j = -t, at + 4
                t = self.best[node]
                while j < n and (node := trie.get(node << 8 | word[j], -1)) >= 0:
                    j += 1
                    if ends[node] >= 0:
                        t = ends[node]
            while True:
                if t < 0:  # no arc from here: step back and take a shorter one
                    dead.add(at)
                    t = path.pop()
                    at -= size[t]
                    s = state[path[-1]] if path else 0
                elif at + size[t] not in dead and ((known := arcs.get(s << 32 | t)) or (known is None and allows(s, t))):
                    path.append(t)
                    at += size[t]
                    s = state[t]
                    break
                t = shorter[t]
        return tuple(path)

    def split(self, text: str) -> list[str]:
        return (_QUICK if text.isascii() and not _SEPARATORS.search(text) else self._split).findall(text)

    def encode(self, text: str) -> list[int]:
        if self._cut is None or not any(t in text for t in self.special):
            return list(chain.from_iterable(map(self.words.__getitem__, self.split(text))))
        out: list[int] = []
        for part in self._cut.split(text):
            if part in self.special:
                out.append(self.special[part])
            else:
                out.extend(chain.from_iterable(map(self.words.__getitem__, self.split(part))))
        return out

    def decode(self, ids: list[int]) -> str:
        if ids and not 0 <= min(ids) <= max(ids) < len(self.spelling):
            ids = [i for i in ids if 0 <= i < len(self.spelling)]
        return self.spell(ids)

    def spell(self, ids: list[int]) -> str:
        """The labels of ids that are all in the vocabulary."""
        return b"".join(map(self.spelling.__getitem__, ids)).decode("utf-8", "replace")


def encode(docs: DataFrame, automaton: MergeAutomaton, text_col: str = "text", ids_col: str = "ids") -> DataFrame:
    """All columns of docs (one named as ids_col is replaced) and the token ids of the text."""
    return _added(docs, automaton, text_col, {ids_col: "array<int>"}, lambda tool, text: (tool.encode(text or ""),))


def decode(tokens: DataFrame, automaton: MergeAutomaton, ids_col: str = "ids", text_col: str = "decoded") -> DataFrame:
    """All columns of tokens (one named as text_col is replaced) and the text that the ids spell; null ids: empty."""
    return _added(tokens, automaton, ids_col, {text_col: "string"}, lambda tool, ids: (tool.decode(ids or ()),))


def round_trip(docs: DataFrame, automaton: MergeAutomaton, text_col: str = "text", ids_col: str = "ids", decoded_col: str = "decoded") -> DataFrame:
    """encode, then decode of its ids, in one pass over the rows."""

    def both(tool: MergeAutomaton, text: str | None) -> tuple[list[int], str]:
        ids = tool.encode(text or "")
        return ids, tool.spell(ids)

    return _added(docs, automaton, text_col, {ids_col: "array<int>", decoded_col: "string"}, both)


def _added(df: DataFrame, automaton: MergeAutomaton, source: str, made: dict[str, str], one) -> DataFrame:
    machine = df.sparkSession.sparkContext.broadcast(automaton)
    kept = [c for c in df.columns if c not in made]
    asked, at_source = asked_of(df, kept, source)
    kinds = [pa.list_(pa.int32()) if kind.startswith("array") else pa.string() for kind in made.values()]

    def run(batches):
        held("bpe")  # a machine keeps its words itself, as long as its broadcast
        tool = machine.value
        for whole in batches:
            for at in range(0, whole.num_rows, ROWS):
                batch = whole.slice(at, ROWS)
                out = zip(*(one(tool, x) for x in batch.column(at_source).to_pylist()), strict=True)
                arrays = [pa.array(values, kind) for values, kind in zip(out, kinds, strict=True)]
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(kept)], *arrays], names=[*kept, *made])

    schema = df.select(*kept, *(F.lit(None).cast(kind).alias(c) for c, kind in made.items())).schema
    return asked.mapInArrow(run, schema)
