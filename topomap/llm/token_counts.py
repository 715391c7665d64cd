"""Token counts by rank-synchronous array merging.

Pre-tokens of a batch of texts lie in one ragged numpy array of symbols. In each round
every sequence finds its own lowest-ranked adjacent pair, and all sequences apply their
pair at once; sequences without a pair leave with their symbol count. Since a merge's
product is only used by later merges, applying all places of a sequence's lowest pair in one
round gives what one-at-a-time merging gives.

Each text is cut where a white-space character follows another character: no pre-token
crosses such a place, so the pieces are independent and each distinct piece is merged once per task.

Null and empty texts have 0 bytes and 0 tokens. Repeated rows each get their row. A text of
any length is cut piece by piece. Other columns of the input don't matter.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import per_worker, without_gc

#: The pre-token rule that byte-level files without a pattern of their own imply (fixed value).
BYTE_LEVEL_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
NO_PAIR = np.int64(1) << 40


def _byte_chars() -> list[str]:
    """Characters that stand for the bytes 0 to 255 in byte-level vocabularies: printable ones for themselves, others from U+0100 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b if b in plain else next(spare)) for b in range(256)]


class PairTable:
    """Open-addressed table from a symbol pair to (rank, product)."""

    def __init__(self, lefts: np.ndarray, rights: np.ndarray, products: np.ndarray, width: int):
        self.width = np.int64(width)
        keys = lefts.astype(np.int64) * self.width + rights
        self.bits = max(10, int(len(keys) * 8).bit_length())
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.ranks = np.full(1 << self.bits, NO_PAIR, np.int64)
        self.products = np.zeros(1 << self.bits, np.int64)
        todo = np.arange(len(keys))
        slots = self._slot(keys)
        while len(todo):
            free = self.keys[slots] == -1
            first = np.zeros(len(todo), bool)
            first[np.unique(slots, return_index=True)[1]] = True
            put = free & first
            at, who = slots[put], todo[put]
            self.keys[at], self.ranks[at], self.products[at] = keys[who], who, products[who]
            todo, slots = todo[~put], slots[~put]
            taken = self.keys[slots] != -1
            slots[taken] = (slots[taken] + 1) & (len(self.keys) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Slot of each pair, or that of an empty place, whose rank is NO_PAIR."""
        keys = left * self.width + right
        slots = self._slot(keys)
        held = self.keys[slots]
        open_ = np.flatnonzero((held != keys) & (held != -1))
        while len(open_):
            slots[open_] = (slots[open_] + 1) & (len(self.keys) - 1)
            held = self.keys[slots[open_]]
            open_ = open_[(held != keys[open_]) & (held != -1)]
        return slots


class RankMerger:
    """Counts the tokens of byte-level pre-tokens from a tokenizer file's vocabulary and merges."""

    def __init__(self, spec: dict):
        vocab = spec["model"]["vocab"]
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        as_ids = lambda strings: np.fromiter((vocab[s] for s in strings), np.int64, len(pairs))
        self.table = PairTable(as_ids(p[0] for p in pairs), as_ids(p[1] for p in pairs), as_ids(p[0] + p[1] for p in pairs), max(vocab.values()) + 1)
        self.of_byte = np.array([vocab[c] for c in _byte_chars()], np.int64)

    def count(self, pretokens: list[bytes]) -> np.ndarray:
        """Symbols that remain of each pre-token once no pair is left."""
        lengths = np.fromiter(map(len, pretokens), np.int64, len(pretokens))
        out = lengths.copy()
        seq = np.flatnonzero(lengths > 1)
        symbols = self.of_byte[np.frombuffer(b"".join([pretokens[i] for i in seq]), np.uint8)]
        lengths = lengths[seq]
        while len(seq):
            starts = np.cumsum(lengths) - lengths
            owner = np.repeat(np.arange(len(seq)), lengths)
            slots = np.zeros(len(symbols), np.int64)
            rank = np.full(len(symbols), NO_PAIR, np.int64)
            inner = owner[:-1] == owner[1:]
            slots[:-1] = self.table.find(symbols[:-1], symbols[1:])
            rank[:-1][inner] = self.table.ranks[slots[:-1][inner]]
            lowest = np.minimum.reduceat(rank, starts)
            hit = (rank == lowest[owner]) & (rank < NO_PAIR)
            # of overlapping places (a run of equal symbols) every other one counts, from the left
            at = np.flatnonzero(hit)
            new_run = np.ones(len(at), bool)
            new_run[1:] = np.diff(at) > 1
            run_start = np.maximum.accumulate(np.where(new_run, np.arange(len(at)), 0))
            at = at[(np.arange(len(at)) - run_start) % 2 == 0]
            symbols[at] = self.table.products[slots[at]]
            lengths = lengths - np.bincount(owner[at], minlength=len(seq))
            stay = np.ones(len(symbols), bool)
            stay[at + 1] = False
            alive = (lowest < NO_PAIR) & (lengths > 1)
            done = ~alive
            out[seq[done]] = lengths[done]
            stay &= alive[owner]
            symbols, seq, lengths = symbols[stay], seq[alive], lengths[alive]
        return out


class PieceCounter:
    """Token counts of whole texts; counts of distinct pieces are kept up to ``memo_limit`` of them."""

    def __init__(self, tokenizer_json: str, memo_limit: int = 600_000):
        spec = json.loads(tokenizer_json)
        self.merger = RankMerger(spec)
        self.pattern = regex.compile(BYTE_LEVEL_PATTERN)
        self.ragged_cut = regex.compile(r"\s ")
        self.pieces_of = regex.compile(r"\s*\S+|\s+")
        specials = sorted((a["content"] for a in spec.get("added_tokens", ())), key=len, reverse=True)
        self.specials = regex.compile("|".join(map(regex.escape, specials))) if specials else None
        self.memo: dict[str, int] = {}
        self.memo_limit = memo_limit

    def _pieces(self, text: str) -> list[str]:
        if self.ragged_cut.search(text):
            return self.pieces_of.findall(text)
        head, *rest = text.split(" ")
        return ([head] if head else []) + [" " + r for r in rest]

    def _learn(self, pieces: list[str]) -> None:
        found = list(map(self.pattern.findall, pieces))
        index: dict[str, int] = {}
        at = np.fromiter((index.setdefault(t, len(index)) for t in chain.from_iterable(found)), np.int64)
        sizes = np.fromiter(map(len, found), np.int64, len(found))
        counts = self.merger.count([t.encode("utf-8", "surrogatepass") for t in index])
        sums = np.add.reduceat(counts[at], np.cumsum(sizes) - sizes)
        self.memo.update(zip(pieces, sums.tolist()))

    def count(self, texts: list[str]) -> list[int]:
        """Tokens of each text. Memory grows with the texts given at once and with the memo."""
        base, parts = [], []
        for text in texts:
            segments = [text] if self.specials is None else self.specials.split(text)
            base.append(len(segments) - 1)
            parts.append(list(chain.from_iterable(self._pieces(s) for s in segments if s)))
        distinct = set().union(*parts)
        unknown = [p for p in distinct if p not in self.memo]
        if len(self.memo) + len(unknown) > self.memo_limit:
            self.memo.clear()
            unknown = list(distinct)
        for lo in range(0, len(unknown), 100_000):
            self._learn(unknown[lo : lo + 100_000])
        get = self.memo.__getitem__
        return [b + sum(map(get, ps)) for b, ps in zip(base, parts)]


def count_tokens(documents: DataFrame, tokenizer_path: str, limit: int, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, n_bytes, n_tokens, over_limit for each row; narrow, without a shuffle.

    ``tokenizer_path``: a byte-level BPE file, read on the driver and shipped with the tasks (a few MB).
    """
    with open(tokenizer_path, encoding="utf-8") as f:
        spec = f.read()
    data = documents.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = per_worker(("counter", hash(spec)), lambda: PieceCounter(spec))
        for batch in batches:
            texts = pc.fill_null(batch.column("text"), "")
            n_bytes = pc.cast(pc.binary_length(texts), pa.int64())
            counts: list[int] = []
            sizes = n_bytes.to_pylist()
            lo = 0
            while lo < len(sizes):  # about 4 MB of text at a time
                hi, held = lo, 0
                while hi < len(sizes) and (hi == lo or held + sizes[hi] <= 4_000_000):
                    held += sizes[hi]
                    hi += 1
                counts += counter.count(texts.slice(lo, hi - lo).to_pylist())
                lo = hi
            n = pa.array(counts, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("id"), n_bytes, n, pc.greater(n, limit)], ["id", "n_bytes", "n_tokens", "over_limit"])

    kind = data.schema["id"].dataType.simpleString()
    return data.mapInArrow(without_gc(run), f"id {kind}, n_bytes bigint, n_tokens bigint, over_limit boolean").withColumnRenamed("id", id_col)
