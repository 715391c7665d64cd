"""Suffix-array dedup: bytes covered by a string of fixed length that an earlier document holds are removed.

Only suffixes around shared anchors take part (see ``windows``). They are range-partitioned by their leading bytes with splitters that Spark
samples; a bucket sorts its suffixes by multikey quicksort, eight bytes as one key, and reads repeats off runs of equal
strings. A splitter is a whole leading string, so suffixes that could be equal share a bucket, and a comparison across its borders can find nothing.

Null and empty texts, and texts shorter than the string, lose nothing. Null ids keep their text. Matches never cross documents.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .windows import Contexts, Units, covered_mask, covered_ranges, grouped_contexts, keyed

BYTES = Units("bytes", 50, 24)


def multikey_sort(group: np.ndarray, keys) -> np.ndarray:
    """Group numbers, refined so that only strings equal in every key share one. ``keys`` give the k-th key of the given rows.

    Each round sorts, within every group that still has several members, by the next key; groups of one are done.
    """
    group = group.astype(np.int64)
    rows = np.arange(len(group))
    top = int(group.max()) + 1 if len(group) else 0
    for key in keys:
        counts = np.bincount(group[rows], minlength=top)
        rows = rows[counts[group[rows]] > 1]
        if not len(rows):
            break
        k = key(rows)
        order = np.lexsort((k, group[rows]))
        rows, k = rows[order], k[order]
        g = group[rows]
        new = np.ones(len(rows), bool)
        new[1:] = (g[1:] != g[:-1]) | (k[1:] != k[:-1])
        group[rows] = top + np.cumsum(new) - 1
        top += int(new.sum())
    return group


#: Runs of so many suffixes at most are compared pair by pair.
FEW = 6


def resolve(units: Units, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A bucket: its suffixes come in runs of equal leading strings. Short runs are compared neighbour by neighbour in both directions
    from the leading string; in long ones the suffixes of all windows are sorted by multikey quicksort."""
    for c in grouped_contexts(batches, 50_000):
        first = np.flatnonzero(np.diff(c.lead, prepend=-1))
        sizes = np.diff(np.append(first, len(c)))
        grid = _grid(units, c)
        for m in range(2, FEW + 1):
            at = first[sizes == m]
            for i in range(m):
                for j in range(i + 1, m):
                    yield from _pairs(units, c, grid, at + i, at + j)
        rows = np.flatnonzero(np.repeat(sizes > FEW, sizes))
        for lo, hi in _whole_runs(c.lead[rows], 12_000):
            yield _sorted_windows(units, c, grid, rows[lo:hi])


def _grid(units: Units, c: Contexts) -> np.ndarray:
    """The contexts as rows of bytes in which all anchors stand in one column."""
    grid = np.zeros((len(c), units.width + units.reach + 16), np.uint8)
    row = np.repeat(np.arange(len(c)), c.size)
    within = np.arange(int(c.size.sum())) - np.repeat(np.cumsum(c.size) - c.size, c.size)
    grid[row, within + np.repeat(units.reach - c.rel, c.size)] = c.flat[np.repeat(c.begin, c.size) + within]
    return grid


def _whole_runs(lead: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    lo = 0
    while lo < len(lead):
        hi = min(len(lead), lo + most)
        while hi < len(lead) and lead[hi] == lead[hi - 1]:
            hi += 1
        yield lo, hi
        lo = hi


def _pairs(units: Units, c: Contexts, grid: np.ndarray, a: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Ranges that the later document of each pair shares with the earlier one around the common anchor."""
    apart = c.doc[a] != c.doc[b]
    a, b = a[apart], b[apart]
    if not len(a):
        return
    reach, end = units.reach, units.reach + units.gram
    stop = np.ones((len(a), 1), bool)
    left = np.argmax(np.concatenate(((grid[a, :reach] != grid[b, :reach])[:, ::-1], stop), axis=1), axis=1)
    left = np.minimum(left, np.minimum(c.rel[a], c.rel[b]))
    right = np.argmax(np.concatenate((grid[a, end : end + reach] != grid[b, end : end + reach], stop), axis=1), axis=1)
    right = np.minimum(right, np.minimum(c.size[a] - c.rel[a], c.size[b] - c.rel[b]) - units.gram)
    hit = left + right >= reach
    late = np.where(c.doc[a] > c.doc[b], a, b)[hit]
    anchor = c.start[late] + c.rel[late]
    yield _range_rows(c.doc[late], c.h[late], anchor - left[hit], anchor + units.gram + right[hit])


def _sorted_windows(units: Units, c: Contexts, grid: np.ndarray, rows: np.ndarray) -> pa.RecordBatch:
    width = units.width
    shifts = np.arange(units.reach + 1)
    begin = units.reach - c.rel[rows]  # column where a row's bytes begin
    fits = (shifts >= begin[:, None]) & (shifts + width <= (begin + c.size[rows])[:, None])
    r, s = np.nonzero(fits)
    own = rows[r]
    keys = [lambda at_rows, at=at: sum(grid[own[at_rows], s[at_rows] + at + b].astype(np.uint64) << np.uint64(8 * (7 - b)) for b in range(min(8, width - at))) for at in range(0, width, 8)]
    group = multikey_sort(np.unique(c.lead[rows], return_inverse=True)[1][r] * (units.reach + 1) + s, keys)
    _, group = np.unique(group, return_inverse=True)
    least = np.full(int(group.max()) + 1 if len(group) else 0, np.iinfo(np.int64).max)
    np.minimum.at(least, group, c.doc[own])
    hit = np.zeros((len(rows), units.reach + 2), bool)
    hit[r, s] = least[group] < c.doc[own]
    return ranges_of(hit, c.doc[rows], c.h[rows], c.start[rows] - begin, width)


def _range_rows(doc, h, start, stop) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.asarray(x, np.int64)) for x in (doc, h, start, stop)], ["doc", "h", "start", "stop"])


def ranges_of(hit: np.ndarray, doc: np.ndarray, h: np.ndarray, origin: np.ndarray, width: int) -> pa.RecordBatch:
    """(doc, h, start, stop) of the runs of windows that ``hit`` marks; its last column is False."""
    edge = np.diff(np.concatenate((np.zeros((len(hit), 1), bool), hit), axis=1).astype(np.int8), axis=1)
    r, a = np.nonzero(edge == 1)
    _, b = np.nonzero(edge == -1)
    return _range_rows(doc[r], h[r], origin[r] + a, origin[r] + b - 1 + width)


def remove_repeated_bytes(documents: DataFrame, units: Units = BYTES, *, id_col: str = "doc_id", text_col: str = "text", keep_bytes: bool = False) -> DataFrame:
    """``id_col``, n_bytes, n_removed, n_spans, kept_sha256 per row; with ``keep_bytes`` also kept (binary)."""
    ranges = covered_ranges(documents, units, resolve, by_range=True, id_col=id_col, text_col=text_col)
    data = keyed(documents, id_col, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text, ranges in zip(batch.column("text"), batch.column("ranges")):
                raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
                if not ranges.is_valid:
                    rows.append((len(raw), 0, 0, hashlib.sha256(raw).hexdigest(), raw))
                    continue
                gone = covered_mask(len(raw), ranges.values)
                kept = np.frombuffer(raw, np.uint8)[~gone].tobytes()
                spans = int(np.count_nonzero(np.diff(gone.astype(np.int8), prepend=0) == 1))
                rows.append((len(raw), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest(), kept))
            columns = [pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())[: 5 if keep_bytes else 4])]
            yield pa.RecordBatch.from_arrays([batch.column("id"), *columns], ["id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"][: len(columns) + 1])

    schema = "id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + (", kept binary" if keep_bytes else "")
    return data.join(ranges, ["id", "h"], "left").select("id", "text", "ranges").mapInArrow(run, schema).withColumnRenamed("id", id_col)
