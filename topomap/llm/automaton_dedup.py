"""Substring dedup over words by suffix automata.

The reference of a corpus deduplicated against itself is the corpus, which has no size bound to broadcast; so its shards are the contexts around
shared anchors (see ``windows``), sent to tasks by anchor. A task builds the suffix automaton of its reference shard, piece by piece, and streams
the contexts through it: the matching statistics at each word give the state of the last ``width`` words, whose smallest document says whether an
earlier document holds the window. Windows that hit mark maximal spans to remove.

Null, empty and blank texts have no words. Texts under ``width`` words lose nothing. Null ids keep their words. Words are compared by 64-bit hash.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .suffix_dedup import ranges_of
from .windows import Units, covered_mask, covered_ranges, grouped_contexts, keyed, word_grams

WORDS = Units("words", 13, 7)
_WORD = re.compile("[^\x20\x09-\x0d]+")


class SuffixAutomaton:
    """Automaton of several sequences; each state knows the smallest document among the places where its strings end."""

    def __init__(self):
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length, self.least = [-1], [0], [np.iinfo(np.int64).max]

    def _state(self, length: int, link: int, edges: dict, least: int) -> int:
        self.next.append(edges)
        self.length.append(length)
        self.link.append(link)
        self.least.append(least)
        return len(self.next) - 1

    def _split(self, p: int, q: int, symbol: int) -> int:
        clone = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]), np.iinfo(np.int64).max)
        self.link[q] = clone
        while p >= 0 and self.next[p].get(symbol) == q:
            self.next[p][symbol] = clone
            p = self.link[p]
        return clone

    def add(self, sequence: list[int], document: int) -> None:
        at = 0
        for symbol in sequence:
            q = self.next[at].get(symbol)
            if q is not None:
                at = q if self.length[q] == self.length[at] + 1 else self._split(at, q, symbol)
            else:
                new = self._state(self.length[at] + 1, 0, {}, np.iinfo(np.int64).max)
                p = at
                while p >= 0 and symbol not in self.next[p]:
                    self.next[p][symbol] = new
                    p = self.link[p]
                if p >= 0:
                    q = self.next[p][symbol]
                    self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, q, symbol)
                at = new
            if document < self.least[at]:
                self.least[at] = document

    def finish(self) -> None:
        """Hand the smallest documents on to the suffixes of each state's strings."""
        for s in sorted(range(1, len(self.next)), key=self.length.__getitem__, reverse=True):
            up = self.link[s]
            if self.least[s] < self.least[up]:
                self.least[up] = self.least[s]

    def earliest(self, sequence: list[int], width: int) -> list[int]:
        """For each window of the sequence the smallest document that holds it."""
        out, at, matched = [], 0, 0
        for i, symbol in enumerate(sequence):
            while at and symbol not in self.next[at]:
                at = self.link[at]
                matched = self.length[at]
            if symbol in self.next[at]:
                at, matched = self.next[at][symbol], matched + 1
            if matched >= width:  # the state of just the last ``width`` symbols
                while self.length[self.link[at]] >= width:
                    at = self.link[at]
                matched = min(matched, self.length[at])
            if i >= width - 1:
                out.append(self.least[at] if matched >= width else np.iinfo(np.int64).max)
        return out


def resolve(units: Units, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    width = units.width
    for c in grouped_contexts(batches, 20_000):
        sizes = c.size // 8
        lo = int(c.begin[0])
        flat = c.flat[lo : lo + 8 * int(sizes.sum())].view(np.uint64)
        begins = np.cumsum(sizes) - sizes
        owner = np.repeat(np.arange(len(c)), sizes)
        # windows by fingerprint: those without a second document match nothing, so only contexts with a shared window need the automaton
        prints = word_grams(flat, width)
        at = np.arange(len(prints))
        inside = at + width <= (begins + sizes)[owner[: len(prints)]]
        prints, at = prints[inside], at[inside]
        _, group = np.unique(prints, return_inverse=True)
        docs = c.doc[owner[at]]
        least = np.full(int(group.max()) + 1 if len(group) else 0, np.iinfo(np.int64).max)
        most = np.full(len(least), np.iinfo(np.int64).min)
        np.minimum.at(least, group, docs)
        np.maximum.at(most, group, docs)
        wanted = np.unique(owner[at[(least < most)[group]]])
        context = {i: flat[begins[i] : begins[i] + sizes[i]].tobytes() for i in wanted.tolist()}
        # one reference per distinct context, its smallest document
        distinct: dict[bytes, int] = {}
        for i, own in context.items():
            distinct[own] = min(distinct.get(own, np.iinfo(np.int64).max), int(c.doc[i]))
        automaton = SuffixAutomaton()
        sequences = {own: np.frombuffer(own, np.uint64).tolist() for own in distinct}
        for own, d in distinct.items():
            automaton.add(sequences[own], d)
        automaton.finish()
        earliest = {own: automaton.earliest(s, width) for own, s in sequences.items()}
        hit = np.zeros((len(wanted), units.reach + 2), bool)
        for k, i in enumerate(wanted.tolist()):
            found = earliest[context[i]]
            hit[k, : len(found)] = np.asarray(found) < c.doc[i]
        yield ranges_of(hit, c.doc[wanted], c.h[wanted], c.start[wanted], width)


def remove_repeated_words(documents: DataFrame, units: Units = WORDS, *, id_col: str = "doc_id", text_col: str = "text", keep_text: bool = False) -> DataFrame:
    """``id_col``, n_words, n_removed, kept_sha256 per row; with ``keep_text`` also kept, its words joined by one space."""
    ranges = covered_ranges(documents, units, resolve, by_range=False, id_col=id_col, text_col=text_col)
    data = keyed(documents, id_col, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text, ranges in zip(batch.column("text"), batch.column("ranges")):
                words = _WORD.findall(text.as_py() or "")
                gone = covered_mask(len(words), ranges.values if ranges.is_valid else None)
                kept = " ".join([w for w, g in zip(words, gone.tolist()) if not g] if ranges.is_valid else words)
                rows.append((len(words), int(gone.sum()), hashlib.sha256(kept.encode("utf-8", "surrogatepass")).hexdigest(), kept))
            columns = [pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.string(), pa.string())[: 4 if keep_text else 3])]
            yield pa.RecordBatch.from_arrays([batch.column("id"), *columns], ["id", "n_words", "n_removed", "kept_sha256", "kept"][: len(columns) + 1])

    schema = "id bigint, n_words bigint, n_removed bigint, kept_sha256 string" + (", kept string" if keep_text else "")
    return data.join(ranges, ["id", "h"], "left").select("id", "text", "ranges").mapInArrow(run, schema).withColumnRenamed("id", id_col)
