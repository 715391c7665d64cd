"""Repeats across documents: exact search for windows of fixed length, without moving all windows.

A document is a sequence of symbols (bytes, or word hashes). Wanted is, for every document, the symbols covered by a window of
``width`` symbols that also starts in a document with a smaller id.

1. Winnowing picks anchors: in every window, the gram of ``gram`` symbols with the least hash. Equal windows pick the same anchor,
   so two documents with a common window share that anchor's hash. Only (hash, id, position) is shuffled. A task settles what repeats
   within it beforehand, so a hash that many documents share is sent once per task; a repeated text is told by a hash of the whole text.
2. Documents with shared anchors give each such anchor's context, the symbols that windows around it can reach. Equal contexts within a
   task are settled there; one of each is sent on.
   Leads of very many contexts are settled once more across tasks.
3. A resolver compares the contexts of equal anchors and tells which windows have an earlier document.
4. The covered ranges go back to their documents.

Documents shorter than ``width`` have no window. Rows with a null id take no part and keep their text. Rows that repeat an id are one document
with several texts: they aren't earlier than each other, and each text loses what an earlier document holds of it. Beside the id, a row is known by a hash of its text.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared
from .shingles import hash_words, mix

ANCHOR, KNOWN, NOTICE = 0, 1, 2
#: Anchors that a task settles at a time.
SETTLE = 1_500_000


def _table() -> np.ndarray:
    return mix((np.arange(256, dtype=np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))


_BYTE_HASH = _table()
_BASE = 0x5851F42D4C957F2D


def byte_grams(data: np.ndarray, gram: int) -> np.ndarray:
    """Hashes of all ``gram``-byte strings, by doubling."""
    part, size = _BYTE_HASH[data], 1
    done, have = None, 0
    rest = gram
    while True:
        if rest & 1:
            if done is None:
                done, have = part, size
            else:  # done covers the last ``have`` bytes; put this part before them
                n = max(0, len(part) - have)
                done = part[:n] * np.uint64(pow(_BASE, have, 1 << 64)) + done[size : size + n]
                have += size
        rest >>= 1
        if not rest:
            break
        n = max(0, len(part) - size)
        part = part[:n] * np.uint64(pow(_BASE, size, 1 << 64)) + part[size : size + n]
        size *= 2
    return mix(done[: max(0, len(data) - gram + 1)]) | np.uint64(1)


def word_grams(words: np.ndarray, gram: int) -> np.ndarray:
    n = max(0, len(words) - gram + 1)
    out = np.zeros(n, np.uint64)
    for k in range(gram):
        out = mix(out ^ words[k : k + n]) + np.uint64(k)
    return out | np.uint64(1)


def _slide(x: np.ndarray, w: int, pick) -> np.ndarray:
    size = 1
    while size * 2 <= w:
        x = pick(x[:-size], x[size:])
        size *= 2
    return pick(x[: len(x) - (w - size)], x[w - size :]) if w > size else x


def winnow(grams: np.ndarray, w: int) -> np.ndarray:
    """Places that are the least of some ``w`` neighbours."""
    if len(grams) < w:
        return np.zeros(0, np.int64)
    least = _slide(grams, w, np.minimum)
    pad = np.zeros(w - 1, np.uint64)
    return np.flatnonzero(_slide(np.concatenate((pad, least, pad)), w, np.maximum) == grams)


@dataclass(frozen=True)
class Units:
    """How texts are symbols: ``bytes`` or ``words``, and the lengths of windows and grams."""

    kind: str
    width: int
    gram: int

    def symbols(self, text: str) -> np.ndarray:
        data = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
        return data if self.kind == "bytes" else hash_words(data)[2]

    def grams(self, symbols: np.ndarray) -> np.ndarray:
        return byte_grams(symbols, self.gram) if self.kind == "bytes" else word_grams(symbols, self.gram)

    @property
    def reach(self) -> int:
        """Symbols before an anchor that a window around it can hold."""
        return self.width - self.gram


def _batches_of(texts: list[np.ndarray], most: int) -> Iterator[tuple[int, int]]:
    lo = held = 0
    for i, t in enumerate(texts):
        held += len(t)
        if held >= most or i == len(texts) - 1:
            yield lo, i + 1
            lo, held = i + 1, 0


def find_anchors(units: Units, symbols: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(gram hash, index in ``symbols``, position) of every anchor; winnowing runs over many texts at once, grams across texts don't count."""
    keys, whose, places = [], [], []
    for lo, hi in _batches_of(symbols, 200_000):
        own = [i for i in range(lo, hi) if len(symbols[i]) >= units.width]
        if not own:
            continue
        data = np.concatenate([symbols[i] for i in own])
        sizes = np.fromiter((len(symbols[i]) for i in own), np.int64, len(own))
        ends = np.cumsum(sizes)
        grams = units.grams(data)
        at = winnow(grams, units.reach + 1)
        doc = np.searchsorted(ends, at, side="right")
        inside = at + units.gram <= ends[doc]
        at, doc = at[inside], doc[inside]
        keys.append(grams[at])
        whose.append(np.asarray(own)[doc])
        places.append(at - (ends - sizes)[doc])
    none = np.zeros(0, np.int64)
    return (np.concatenate(keys), np.concatenate(whose), np.concatenate(places)) if keys else (none.astype(np.uint64), none, none)


def _runs(*columns: np.ndarray) -> np.ndarray:
    """Number of the run of equal rows for sorted columns."""
    new = np.zeros(len(columns[0]), bool)
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return np.cumsum(new)


def settle_anchors(keys, docs, places) -> tuple[np.ndarray, ...]:
    """(route, id, place, kind) rows to send: what repeats here is KNOWN, with one NOTICE per hash for the others; the rest asks as ANCHOR."""
    order = np.lexsort((docs, keys))
    keys, docs, places = keys[order], docs[order], places[order]
    run = _runs(keys)
    first = np.flatnonzero(np.diff(run, prepend=-1))
    last = np.append(first[1:], len(run)) - 1
    repeats = (docs[first] != docs[last])[run] if len(run) else np.zeros(0, bool)
    notice = first[docs[first] != docs[last]]
    kinds = np.where(repeats, KNOWN, ANCHOR)
    routes = np.where(repeats, mix(docs.view(np.uint64) + np.uint64(7)), keys)
    return (
        np.concatenate((routes, keys[notice])),
        np.concatenate((docs, docs[notice])),
        np.concatenate((places, places[notice])),
        np.concatenate((kinds, np.full(len(notice), NOTICE))),
    )


def text_prints(symbols: np.ndarray) -> tuple[int, int]:
    raw = symbols.tobytes()
    return xxhash.xxh3_64_intdigest(raw), xxhash.xxh64_intdigest(raw, 11)


def copy_place(print_: int) -> int:
    """The second hash of a text as a negative place."""
    return -1 - (print_ >> 4)


def settle_copies(prints: list[tuple[int, int]], docs: np.ndarray) -> tuple[np.ndarray, ...]:
    """Whole-text rows: place is negative and carries the second hash. All but the smallest id of equal texts are KNOWN copies."""
    if not len(docs):
        return np.zeros(0, np.uint64), docs, docs, docs
    one = np.fromiter((p[0] for p in prints), np.uint64, len(docs))
    two = np.fromiter((copy_place(p[1]) for p in prints), np.int64, len(docs))
    order = np.lexsort((docs, two, one))
    one, two, docs = one[order], two[order], docs[order]
    run = _runs(one, two)
    first = np.flatnonzero(np.diff(run, prepend=-1))
    copy = docs != docs[first][run]
    return np.where(copy, mix(docs.view(np.uint64) + np.uint64(7)), one), docs, two, np.where(copy, KNOWN, ANCHOR)


def _anchor_rows(units: Units) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []
        copies: list = []
        n = 0

        def flush() -> pa.RecordBatch:
            rows = [settle_anchors(*map(np.concatenate, zip(*held)))] if held else []
            if copies:
                rows.append(settle_copies([c[0] for c in copies], np.fromiter((c[1] for c in copies), np.int64, len(copies))))
            route, doc, place, kind = (np.concatenate(x) for x in zip(*rows))
            held.clear()
            copies.clear()
            packed = (place << 2) | kind
            return pa.RecordBatch.from_arrays([pa.array(route.view(np.int64)), pa.array(doc), pa.array(packed)], ["route", "doc", "packed"])

        for batch in batches:
            ids = batch.column("id").to_numpy()
            texts = batch.column("text")
            for lo in range(0, len(ids), 500):
                part = [t.as_py() or "" for t in texts.slice(lo, 500)]
                symbols = [units.symbols(t) for t in part]
                keys, whose, places = find_anchors(units, symbols)
                if len(keys):
                    held.append((keys, ids[lo + whose], places))
                    n += len(keys)
                for i, s in enumerate(symbols):
                    if len(s) >= units.width:
                        copies.append((text_prints(s), int(ids[lo + i])))
                if n >= SETTLE:
                    yield flush()
                    n = 0
        if held or copies:
            yield flush()

    return run


def match_anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All rows of some routes: gives (doc, place) of anchors that another document has; for copies of an earlier text the negative place of their hash."""
    parts = [tuple(b.column(c).to_numpy() for c in ("route", "doc", "packed")) for b in batches if len(b)]
    if not parts:
        return
    route, doc, packed = (np.concatenate(x) for x in zip(*parts))
    place, kind = packed >> 2, packed & 3
    known = kind == KNOWN
    out_doc, out_place = [doc[known]], [place[known]]
    asks = ~known & (place >= 0)
    order = np.lexsort((doc[asks], route[asks]))
    r, d, p, k = route[asks][order], doc[asks][order], place[asks][order], kind[asks][order]
    if len(r):
        run = _runs(r)
        first = np.flatnonzero(np.diff(run, prepend=-1))
        last = np.append(first[1:], len(run)) - 1
        # a run of one document is not shared; rows of a NOTICE are known already
        hit = (d[first] != d[last])[run] & (k == ANCHOR)
        out_doc.append(d[hit])
        out_place.append(p[hit])
    whole = ~known & (place < 0)
    order = np.lexsort((doc[whole], place[whole], route[whole]))
    r, d, p = route[whole][order], doc[whole][order], place[whole][order]
    if len(r):
        run = _runs(r, p)
        copy = d != d[np.flatnonzero(np.diff(run, prepend=-1))][run]
        out_doc.append(d[copy])
        out_place.append(p[copy])
    docs, places = np.concatenate(out_doc), np.concatenate(out_place)
    for lo in range(0, len(docs), 50_000):
        yield pa.RecordBatch.from_arrays([pa.array(docs[lo : lo + 50_000]), pa.array(places[lo : lo + 50_000])], ["doc", "place"])


_CONTEXT_SCHEMA = "lead binary, doc bigint, h bigint, start bigint, rel int, context binary, stop bigint"
#: Leads of so many contexts in a flush are reported, and leads of so many of all, or of this share of all if that is more, are settled once more before they are compared.
REPORTED, HOT_ROWS, HOT_SHARE = 16, 5_000, 1 / 5_000


class Settler:
    """Keeps one row of equal contexts, that of the smallest document; the others are covered from end to end."""

    schema = pa.schema([("lead", pa.binary()), ("doc", pa.int64()), ("h", pa.int64()), ("start", pa.int64()), ("rel", pa.int32()), ("context", pa.binary()), ("stop", pa.int64())])

    def __init__(self, units: Units, report: bool):
        self.size = 8 if units.kind == "words" else 1
        self.gram, self.report = units.gram, report
        self.best: dict[tuple[bytes, int], tuple[int, int, int, int]] = {}  # context and its anchor's place in it -> smallest document, hash of its text, start, stop
        self.again: list[tuple[tuple[bytes, int], tuple[int, int, int, int]]] = []  # equal contexts elsewhere in the same document
        self.settled: list[tuple[int, int, int, int]] = []

    def __len__(self) -> int:
        return len(self.best) + len(self.again) + len(self.settled)

    def add(self, key: tuple[bytes, int], row: tuple[int, int, int, int]) -> None:
        seen = self.best.get(key)
        if seen is None:
            self.best[key] = row
        elif row[0] < seen[0]:
            self.settled.append(seen)
            self.best[key] = row
        elif row[0] > seen[0]:
            self.settled.append(row)
        elif row != seen:
            self.again.append((key, row))

    def flush(self) -> pa.RecordBatch:
        """Rows to compare, (doc, h, start, stop) rows that are settled, and with ``report`` (lead, count in start) of frequent leads."""
        rows = [(c[rel * self.size : (rel + self.gram) * self.size], d, h, s, rel, c, None) for (c, rel), (d, h, s, e) in [*self.best.items(), *self.again]]
        if self.report:
            frequent = {lead: n for lead, n in Counter(r[0] for r in rows).items() if n >= REPORTED}
            rows += [(lead, None, None, n, None, None, None) for lead, n in frequent.items()]
        rows += [(None, d, h, s, None, None, e) for d, h, s, e in self.settled]
        self.best.clear()
        self.again.clear()
        self.settled.clear()
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows), self.schema.types)], schema=self.schema)


def _context_rows(units: Units) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        settler = Settler(units, report=True)
        size = settler.size
        for batch in batches:
            for row_id, h, text, listed in zip(batch.column("id").to_pylist(), batch.column("h").to_pylist(), batch.column("text"), batch.column("places")):
                symbols = units.symbols(text.as_py() or "")
                places = listed.values.to_numpy()
                n = len(symbols)
                whole = places[places < 0]
                # of an id with several texts, the copy may be another one
                if len(whole) and (whole == copy_place(text_prints(symbols)[1])).any():
                    settler.settled.append((row_id, h, 0, n))
                    continue
                raw = symbols.tobytes()
                for p in np.unique(places[(places >= 0) & (places <= n - units.gram)]).tolist():
                    lo, hi = max(0, p - units.reach), min(n, p + units.width)
                    settler.add((raw[lo * size : hi * size], p - lo), (row_id, h, lo, hi))
                if len(settler) > 60_000:
                    yield settler.flush()
        if len(settler):
            yield settler.flush()

    return run


def _settle_again(units: Units) -> Callable:
    """Contexts of hot leads that other tasks have settled for themselves; equal ones come to one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        settler = Settler(units, report=False)
        for batch in batches:
            for doc, h, start, rel, context in zip(*(batch.column(c).to_pylist() for c in ("doc", "h", "start", "rel", "context"))):
                settler.add((context, rel), (doc, h, start, start + len(context) // settler.size))
        if len(settler):
            yield settler.flush()

    return run


def keyed(documents: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, h, text): the rows with a hash of their text, which tells rows of one id apart."""
    return documents.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("h"), F.col(text_col).alias("text"))


def covered_ranges(documents: DataFrame, units: Units, resolver: Callable, *, by_range: bool, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, h, ranges): for texts with something covered, array of (start, stop) in symbols, overlapping as found.

    ``resolver(units, rows)`` takes Arrow batches (lead, doc, h, start, rel, context) that hold all rows of a lead and gives (doc, h, start, stop).
    """
    data = keyed(documents, id_col, text_col).where("id is not null")
    anchors = data.select("id", "text").mapInArrow(_anchor_rows(units), "route bigint, doc bigint, packed bigint")
    places = anchors.repartition("route").mapInArrow(match_anchors, "doc bigint, place bigint")
    places = shared.materialize(places, "anchor-places")
    lists = places.groupBy(F.col("doc").alias("id")).agg(F.collect_list("place").alias("places"))
    rows = data.join(lists, "id").select("id", "h", "text", "places").mapInArrow(_context_rows(units), _CONTEXT_SCHEMA)
    rows = shared.materialize(rows, "anchor-contexts")
    shared.discard(places)
    made = [rows]
    open_ = rows.where("context is not null").drop("stop")
    # a passage that many documents hold is one context in many tasks: there are at most 1 / HOT_SHARE such leads, whatever the input
    hot = rows.where("doc is null").groupBy("lead").agg(F.sum("start").alias("n")).where(F.col("n") >= max(HOT_ROWS, rows.count() * HOT_SHARE)).select("lead")
    hot = shared.materialize(hot, "hot-leads")
    if not hot.isEmpty():
        settled = open_.join(F.broadcast(hot), "lead", "left_semi").select("doc", "h", "start", "rel", "context").repartition("context").mapInArrow(_settle_again(units), _CONTEXT_SCHEMA)
        made.append(shared.materialize(settled, "hot-contexts"))
        open_ = open_.join(F.broadcast(hot), "lead", "left_anti").unionByName(made[1].where("context is not null").drop("stop"))
    dealt = open_.repartitionByRange("lead") if by_range else open_.repartition("lead")
    ranges = dealt.mapInArrow(lambda batches: resolver(units, batches), "doc bigint, h bigint, start bigint, stop bigint")
    for table in made:
        ranges = ranges.union(table.where("stop is not null").select("doc", "h", "start", "stop"))
    ranges = shared.materialize(ranges, "covered-ranges")
    shared.discard(*made)
    return ranges.groupBy(F.col("doc").alias("id"), "h").agg(F.collect_list(F.struct("start", "stop")).alias("ranges"))


@dataclass
class Contexts:
    """Some contexts in the order of their leads: their bytes one after another, and by context where they begin, their size, lead number, document, text, start and anchor place."""

    flat: np.ndarray
    begin: np.ndarray
    size: np.ndarray
    lead: np.ndarray
    doc: np.ndarray
    h: np.ndarray
    start: np.ndarray
    rel: np.ndarray

    def __len__(self) -> int:
        return len(self.lead)


def grouped_contexts(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[Contexts]:
    """Rows of a partition in pieces of about ``most`` that don't split a lead."""
    parts = [b for b in batches if len(b)]
    if not parts:
        return
    table = pa.Table.from_batches(parts).combine_chunks()
    leads = table.column("lead").combine_chunks().dictionary_encode()
    numbers = (leads.combine_chunks() if isinstance(leads, pa.ChunkedArray) else leads).indices.to_numpy()
    order = np.argsort(numbers, kind="stable")
    numbers = numbers[order]
    doc, h, start, rel = (table.column(c).to_numpy()[order] for c in ("doc", "h", "start", "rel"))
    contexts = table.column("context")
    lo = 0
    while lo < len(order):
        hi = min(len(order), lo + most)
        while hi < len(order) and numbers[hi] == numbers[hi - 1]:
            hi += 1
        taken = contexts.take(pa.array(order[lo:hi]))
        taken = taken.combine_chunks() if isinstance(taken, pa.ChunkedArray) else taken
        taken = taken.chunk(0) if isinstance(taken, pa.ChunkedArray) else taken
        offsets = np.frombuffer(taken.buffers()[1], np.int32)[taken.offset : taken.offset + len(taken) + 1].astype(np.int64)
        flat = np.frombuffer(taken.buffers()[2], np.uint8)
        yield Contexts(flat, offsets[:-1], np.diff(offsets), numbers[lo:hi], doc[lo:hi], h[lo:hi], start[lo:hi], rel[lo:hi].astype(np.int64))
        lo = hi


def covered_mask(n: int, ranges) -> np.ndarray:
    """True where one of the ranges lies; ``ranges`` as Arrow list value or None."""
    mark = np.zeros(n + 1, np.int64)
    if ranges is not None and len(ranges):
        np.add.at(mark, ranges.field("start").to_numpy(), 1)
        np.add.at(mark, ranges.field("stop").to_numpy(), -1)
    return np.cumsum(mark[:-1]) > 0
