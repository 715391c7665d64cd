"""BPE encoding and decoding with content-defined chunk reuse.

A rolling hash over the UTF-8 bytes cuts each text into chunks, so equal passages give equal
chunks wherever they stand. Texts are routed by their smallest chunk hash (copies and near copies
meet), and a task encodes each distinct chunk once. A chunk is kept as its inside, from its first to its
last blank; the joins between insides are repaired by re-encoding: the window over a join takes in
whole words of both neighbours, and grows until its ids agree with theirs at both ends. If a window
would swallow a neighbour, the text is encoded whole.

Ids equal those of the tokenizers library on the whole text, and decoding gives what its ``decode`` gives.
Null and empty texts have no ids and decode to an empty string. Repeated rows each get their row. Routing affects
only how often a chunk is encoded, never a result: a hot route is split by size (REBALANCE). Texts of any length are
cut the same way; a text without blanks is one join. Other columns of the input don't matter.
"""

from __future__ import annotations

import hashlib
import json
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from .shared import per_worker, without_gc

#: Rolling-hash window in bytes (a power of two).
ROLL = 16


def _gear() -> np.ndarray:
    x = (np.arange(256, dtype=np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    return (x >> np.uint64(32)).astype(np.uint32)


GEAR = _gear()


def chunk_cuts(raw: bytes, bits: int, least: int) -> list[int]:
    """Ends of the chunks: places whose rolling hash has ``bits`` zero bits, moved to the next character, ``least`` bytes apart at least."""
    end = len(raw)
    if end <= least:
        return [end] if end else []
    data = np.frombuffer(raw, np.uint8)
    h = GEAR[data]
    step = 1
    while step < ROLL:
        h[step:] += h[:-step] << np.uint32(2 * step)  # numpy reads the right side whole before it writes
        step *= 2
    starts = (data & 0xC0) != 0x80
    cuts, last = [], 0
    for at in (np.flatnonzero((h >> np.uint32(32 - bits)) == 0) + 1).tolist():
        if at - last >= least:
            while at < end and not starts[at]:
                at += 1
            if at < end:
                cuts.append(at)
                last = at
    return [*cuts, end]


class ChunkCodec:
    """Encodes and decodes texts; keeps at most ``word_limit`` words and ``chunk_bytes`` bytes of chunks between calls."""

    def __init__(self, tokenizer_json: str, bits: int = 10, least: int = 256, word_limit: int = 400_000, chunk_bytes: int = 24_000_000):
        self.tokenizer = Tokenizer.from_str(tokenizer_json)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.piecewise = json.loads(tokenizer_json).get("decoder") is None
        self.token = [self.tokenizer.id_to_token(i) or "" for i in range(self.tokenizer.get_vocab_size(with_added_tokens=True))]
        self.number = [str(i) for i in range(len(self.token))]
        self.bits, self.least, self.word_limit, self.chunk_bytes = bits, least, word_limit, chunk_bytes
        self.words: dict[str, tuple[str, str]] = {}
        self.chunks: dict[str, tuple[str, str]] = {}
        self.held = 0
        self.encoded_chunks = self.reused_chunks = self.whole_texts = 0

    def _ids(self, strings: list[str]) -> list[list[int]]:
        return [e.ids for e in self.tokenizer.encode_batch_fast(strings, add_special_tokens=False)]

    def _written(self, ids: list[int]) -> tuple[str, str]:
        return " ".join([self.number[i] for i in ids]), " ".join([self.token[i] for i in ids])

    def _learn_words(self, words: set[str]) -> None:
        new = [w for w in words if w not in self.words]
        if len(self.words) + len(new) > self.word_limit:
            self.words.clear()
            new = list(words)
        for lo in range(0, len(new), 20_000):
            part = new[lo : lo + 20_000]
            self.words.update(zip(part, map(self._written, self._ids(part))))

    def _learn_chunks(self, insides: set[str]) -> None:
        split = {c: c.replace("\n", " ").split(" ") for c in insides}
        self._learn_words({w for ws in split.values() for w in ws if w})
        get = self.words.__getitem__
        for c, ws in split.items():
            pairs = [get(w) for w in ws if w]
            entry = " ".join([p[0] for p in pairs if p[0]]), " ".join([p[1] for p in pairs if p[0]])
            self.chunks[c] = entry
            self.held += len(c) + len(entry[0]) + len(entry[1])

    @staticmethod
    def _inside(chunk: str) -> tuple[int, int]:
        """Where the inside begins and ends: after the first blank, before the last; (len, len) without two blanks."""
        a, b = chunk.find(" "), chunk.find("\n")
        first = min(a, b) if a >= 0 and b >= 0 else max(a, b)
        last = max(chunk.rfind(" "), chunk.rfind("\n"))
        return (first, last) if 0 <= first < last else (len(chunk), len(chunk))

    def encode(self, texts: list[str]) -> list[tuple[str, str]]:
        """For each text its ids in decimal and its tokens, each joined by one space."""
        if self.held > self.chunk_bytes:
            self.chunks.clear()
            self.held = 0
        laid_out, wanted = [], set()
        for text in texts:
            raw = text.encode("utf-8", "surrogatepass")
            at, joins, insides = 0, [""], []
            for cut in chunk_cuts(raw, self.bits, self.least):
                chunk = raw[at:cut].decode("utf-8", "surrogatepass")
                at = cut
                first, last = self._inside(chunk)
                if last == len(chunk):
                    joins[-1] += chunk
                    continue
                joins[-1] += chunk[:first]
                insides.append(chunk[first:last])
                joins.append(chunk[last:])
            laid_out.append((joins, insides))
            for c in insides:
                if c in self.chunks or c in wanted:
                    self.reused_chunks += 1
                else:
                    wanted.add(c)
        self.encoded_chunks += len(wanted)
        self._learn_chunks(wanted)
        repaired = self._repair(laid_out)
        out = []
        for k, (text, (joins, insides)) in enumerate(zip(texts, laid_out)):
            ids: list[str] = []
            tokens: list[str] = []
            if (fixed := repaired[k]) is None:
                self.whole_texts += 1
                whole = self._written(self._ids([text])[0])
                out.append(whole)
                continue
            for j, entry in enumerate(fixed):
                if entry[0]:
                    ids.append(entry[0])
                    tokens.append(entry[1])
                if j < len(insides) and (entry := self.chunks[insides[j]])[0]:
                    ids.append(entry[0])
                    tokens.append(entry[1])
            out.append((" ".join(ids), " ".join(tokens)))
        return out

    @staticmethod
    def _edge(inside: str, n_words: int, at_end: bool) -> str | None:
        """The first or last ``n_words`` words of an inside with the blank before or after them; None if it has fewer."""
        flat = inside.replace("\n", " ").strip(" ")
        parts = flat.rsplit(" ", n_words) if at_end else flat.split(" ", n_words)
        if len(parts) <= n_words or not all(parts[1:] if at_end else parts[:-1]):
            return None
        return " " + " ".join(parts[1:]) if at_end else " ".join(parts[:-1]) + " "

    def _repair(self, laid_out: list) -> list[list[tuple[str, str]] | None]:
        out: list = [[("", "")] * len(joins) for joins, _ in laid_out]
        todo = [(k, j, 1) for k, (joins, insides) in enumerate(laid_out) for j in range(len(joins)) if joins[j] or 0 < j]
        while todo:
            windows, again = [], []
            for k, j, n in todo:
                joins, insides = laid_out[k]
                if out[k] is None:
                    continue
                left = self._edge(insides[j - 1], n, True) if j else ""
                right = self._edge(insides[j], n, False) if j < len(insides) else ""
                if left is None or right is None:
                    out[k] = None
                    continue
                windows.append((k, j, n, left, right))
            if not windows:
                break
            texts = [left + laid_out[k][0][j] + (" " + right if right else "") for k, j, n, left, right in windows]
            for (k, j, n, left, right), ids in zip(windows, self._ids(texts)):
                lead = [i for w in left.split(" ") if w for i in self._of_word(w)]
                trail = [i for w in right.split(" ") if w for i in self._of_word(w)]
                if len(ids) >= len(lead) + len(trail) and ids[: len(lead)] == lead and ids[len(ids) - len(trail) :] == trail:
                    if out[k] is not None:
                        out[k][j] = self._written(ids[len(lead) : len(ids) - len(trail)])
                else:
                    again.append((k, j, 2 * n))
            todo = again
        return out

    def _of_word(self, word: str) -> list[int]:
        known = self.words.get(word)
        if known is None:
            ids = self._ids([word])[0]
            self.words[word] = self._written(ids)
            return ids
        return [int(i) for i in known[0].split(" ")] if known[0] else []

    def decode(self, ids: str, tokens: str) -> str:
        """What the library's decode gives: without a decoder in the file, the tokens joined by a space."""
        if self.piecewise:
            return tokens
        return self.tokenizer.decode([int(i) for i in ids.split(" ")] if ids else [], skip_special_tokens=False)


def route(text: str, bits: int = 10, least: int = 256) -> int:
    """Smallest chunk hash of a text: equal for copies, mostly for near copies."""
    raw, at, smallest = text.encode("utf-8", "surrogatepass"), 0, (1 << 63) - 1
    for cut in chunk_cuts(raw, bits, least):
        smallest = min(smallest, xxhash.xxh3_64_intdigest(raw[at:cut]) >> 1)
        at = cut
    return smallest


def _slices(texts: pa.Array, most: int = 2_000_000) -> Iterator[list[str]]:
    """Lists of texts of about ``most`` characters."""
    lo, held, part = 0, 0, []
    for t in texts:
        s = t.as_py() or ""
        part.append(s)
        held += len(s)
        if held >= most:
            yield part
            part, held = [], 0
    if part:
        yield part


def encode_documents(documents: DataFrame, tokenizer_path: str, *, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """``id_col``, n_tokens, ids_sha256, decoded_sha256 per row; with ``keep_ids`` also ids (array<int>) and decoded.

    ``tokenizer_path``: a tokenizers file, read on the driver and shipped with the tasks (a few MB).
    One shuffle of the texts, by route.
    """
    with open(tokenizer_path, encoding="utf-8") as f:
        spec = f.read()
    data = documents.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = data.schema["id"].dataType.simpleString()

    def routed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            routes = pa.array([route(t.as_py() or "") for t in batch.column("text")], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("text"), routes], ["id", "text", "route"])

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        codec = per_worker(("codec", hash(spec)), lambda: ChunkCodec(spec))
        sha = lambda s: hashlib.sha256(s.encode("utf-8", "surrogatepass")).hexdigest()
        for batch in batches:
            done = 0
            for texts in _slices(batch.column("text")):
                pairs = codec.encode(texts)
                decoded = [codec.decode(*p) for p in pairs]
                columns = [
                    batch.column("id").slice(done, len(texts)),
                    pa.array([p[0].count(" ") + 1 if p[0] else 0 for p in pairs], pa.int64()),
                    pa.array([sha(p[0]) for p in pairs]),
                    pa.array(map(sha, decoded), pa.string()),
                ]
                names = ["id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if keep_ids:
                    columns += [pa.array([[int(i) for i in p[0].split(" ")] if p[0] else [] for p in pairs], pa.list_(pa.int32())), pa.array(decoded, pa.string())]
                    names += ["ids", "decoded"]
                done += len(texts)
                yield pa.RecordBatch.from_arrays(columns, names)

    schema = f"id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded string" if keep_ids else "")
    together = data.mapInArrow(routed, f"id {kind}, text string, route bigint").hint("rebalance", "route")
    return together.mapInArrow(without_gc(coded), schema).withColumnRenamed("id", id_col)
