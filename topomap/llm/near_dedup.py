"""Near-duplicate documents by BagMinHash signatures, bands and verified multiset overlap.

A document is the bag of its five-word shingles; its weight on a shingle is the count. Every shingle owns Poisson processes over
weight layers [0,1), [1,2), [2,4), [4,8) ..., whose points carry a time, a signature place and a weight level; a point counts if
its level lies below the shingle's weight. A place's value is its earliest point, so two bags agree at a place
with probability equal to their weighted Jaccard. The bits of a point's level are the choices of the splits: a layer halves until a half
lies wholly below the weight or above it, and a point above it is dropped. Only points up to a time limit set by the total weight are made; a
bag with an unfilled place is run again with a later limit, so the result doesn't depend on the limit. Times are added in one order per
shingle and rounded before they are hashed, so a signature is a function of the bag alone, whatever else is in its batch.

Equal bags share a class without comparison. Others meet in bands: each is checked by its exact multiset overlap
against the smallest member of each of its buckets, and the links give classes. Then, in each bucket that still holds several classes, members outside
of the bucket's largest class first meet the ``PIVOTS`` most central of it, classes merge, and those still outside meet all others that are of another class. Pairs that can't reach the threshold are not made: every shingle that two bags don't share flips
one of ``PARITY`` parity bits, so bits that differ can't outnumber the shingles that may differ (exact); and one-bit sketches of the signatures
may differ by seven deviations. Thus every pair of a bucket is checked, ruled out, or in one class already, and a large group of near
copies costs a row per member. A class is a connected component.

Null ids, and null, empty and blank texts, link with nothing and stay. Texts under five words are one shingle of all their words. Rows that
repeat a doc_id are one document that takes part with each of its texts. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import shared
from .components import connected_components
from .shingles import mix, multiset_jaccard, shingle_lists

WIDTH = 5
BANDS, ROWS = 32, 5
SKETCH = ("s0", "s1", "s2")
#: Parity bits of a bag, a power of two, and their columns.
PARITY = 512
PARITIES = tuple(f"p{k}" for k in range(PARITY // 64))
_GOLD = 0x9E3779B97F4A7C15
_WORD = (1 << 64) - 1


#: Members of a bucket's largest class that those outside of it meet first.
PIVOTS = 8


def _unit(x: np.ndarray) -> np.ndarray:
    """Scrambled words as numbers in (0, 1]."""
    return ((x >> np.uint64(11)).astype(np.float64) + 1.0) * (2.0**-53)


def bag_signatures(bags: list[np.ndarray], places: int) -> np.ndarray:
    """len(bags) x places times of the earliest points; a bag is its sorted element hashes, with repeats. Empty bags give inf."""
    out = np.full((len(bags), places), np.inf)
    sizes = np.fromiter(map(len, bags), np.int64, len(bags))
    todo, slack = np.flatnonzero(sizes), 3.0
    while len(todo):
        limits = (places / sizes[todo]) * (np.log(places) + slack)
        out[todo] = _points([bags[i] for i in todo], limits, places)
        todo = todo[~np.isfinite(out[todo]).all(axis=1)]
        slack = 2 * slack + places / 8
    return out


def _points(bags: list[np.ndarray], limits: np.ndarray, places: int) -> np.ndarray:
    flat = np.concatenate(bags)
    bag = np.repeat(np.arange(len(bags)), [len(b) for b in bags])
    first = np.ones(len(flat), bool)
    first[1:] = (flat[1:] != flat[:-1]) | (bag[1:] != bag[:-1])
    at = np.flatnonzero(first)
    weight = np.diff(np.append(at, len(flat)))
    element, bag = flat[at], bag[at]
    out = np.full(len(bags) * places, np.inf)
    low, high = 0, 1
    while len(element):  # a layer at a time; few elements have weight above 1
        _layer(element, bag, weight, low, high, limits, places, out)
        low, high = high, 2 * high
        on = weight > low
        element, bag, weight = element[on], bag[on], weight[on]
    return out.reshape(len(bags), places)


def _layer(element, bag, weight, low, high, limits, places, out) -> None:
    seed = mix(element + np.uint64(low * _GOLD & _WORD))
    rate = float(high - low)
    time = np.zeros(len(seed))
    step, block = 0, 1
    while len(seed):
        gaps = np.empty((len(seed), block))
        draws = np.empty((len(seed), block), np.uint64)
        for k in range(block):
            x = mix(seed + np.uint64((step + k + 1) * _GOLD & _WORD))
            gaps[:, k] = np.log(_unit(x))
            draws[:, k] = x
        # one addition after another from the first gap on, so that the size of a block doesn't show
        times = np.cumsum(np.concatenate((time[:, None], -gaps / rate), axis=1), axis=1)[:, 1:]
        hit = times <= limits[bag][:, None]
        r, c = np.nonzero(hit)
        second = mix(draws[r, c] ^ np.uint64(0xA5A5A5A5A5A5A5A5))
        place = (second >> np.uint64(32)) * np.uint64(places) >> np.uint64(32)
        level = low + (second & np.uint64(0xFFFFFFFF)).astype(np.float64) * (rate / 2.0**32)
        counts = level < weight[r]
        np.minimum.at(out, bag[r[counts]] * places + place[counts].astype(np.int64), times[r, c][counts])
        go = hit[:, -1]
        seed, bag, weight, time = seed[go], bag[go], weight[go], times[go, -1]
        step += block
        block = 1 if len(seed) > 100_000 else 16
    return


def rounded_times(times: np.ndarray) -> np.ndarray:
    """Words to hash in place of times: equal for times that differ by the last bits of a logarithm on another machine."""
    return times.astype(np.float32).view(np.uint32).astype(np.uint64)


def parities(bags: list[np.ndarray]) -> np.ndarray:
    """len(bags) x PARITY / 64 words: per cell of the shingle hashes whether the bag holds an odd number of shingles."""
    cells = np.concatenate([np.zeros(0, np.uint64), *bags]) >> np.uint64(64 - (PARITY.bit_length() - 1))
    owner = np.repeat(np.arange(len(bags)), [len(b) for b in bags])
    odd = np.bincount(owner * PARITY + cells.astype(np.int64), minlength=len(bags) * PARITY).reshape(len(bags), PARITY) & 1
    return np.packbits(odd.astype(np.uint8), axis=1).view(np.int64)


def signature_table(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, h, n, f1, f2, bands, ...): hash of the text, shingle count, 128-bit fingerprint of the bag, one 64-bit key per band, sketch and parity bits."""
    data = documents.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("h"), F.col(text_col).alias("text"))
    words = [*SKETCH, *PARITIES]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text")
            lo, held, part = 0, 0, []
            for i in range(len(texts)):
                part.append(texts[i].as_py() or "")
                held += len(part[-1])
                if held > 1_000_000 or i == len(texts) - 1:
                    yield signed(batch.slice(lo, len(part)), part)
                    lo, held, part = i + 1, 0, []

    def signed(rows: pa.RecordBatch, texts: list[str]) -> pa.RecordBatch:
        bags = shingle_lists(texts, WIDTH)
        prints = np.frombuffer(b"".join(hashlib.blake2b(b.tobytes(), digest_size=16).digest() for b in bags), np.int64).reshape(-1, 2)
        times = rounded_times(bag_signatures(bags, BANDS * ROWS)).reshape(len(bags), BANDS, ROWS)
        keys = np.zeros((len(bags), BANDS), np.uint64)
        for k in range(ROWS):
            keys = mix(keys ^ times[:, :, k]) + np.uint64(k)
        flat = pa.array(keys.view(np.int64).ravel())
        bands = pa.ListArray.from_arrays(pa.array(np.arange(len(bags) + 1, dtype=np.int32) * BANDS), flat)
        sizes = pa.array([len(b) for b in bags], pa.int64())
        bits = np.zeros((len(bags), 192), np.uint8)
        bits[:, : BANDS * ROWS] = (mix(times.reshape(len(bags), -1)) >> np.uint64(40)) & np.uint64(1)
        sketch = np.concatenate((np.packbits(bits, axis=1).view(np.int64), parities(bags)), axis=1)
        columns = [rows.column("id"), rows.column("h"), sizes, pa.array(prints[:, 0]), pa.array(prints[:, 1]), bands, *[pa.array(np.ascontiguousarray(sketch[:, k])) for k in range(len(words))]]
        return pa.RecordBatch.from_arrays(columns, ["id", "h", "n", "f1", "f2", "bands", *words])

    return data.mapInArrow(run, "id bigint, h bigint, n bigint, f1 bigint, f2 bigint, bands array<bigint>, " + ", ".join(f"{w} bigint" for w in words))


def sketch_bound(threshold: float) -> int:
    """Bits of a sketch (one per signature place) in which a pair at the threshold may differ: seven deviations above the mean."""
    p = (1 - threshold) / 2
    return int(BANDS * ROWS * p + 7 * (BANDS * ROWS * p * (1 - p)) ** 0.5)


def _verified(pairs: DataFrame, texts: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, ha, b, hb) whose bags overlap enough, as (a, b)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, len(batch), 256):
                part = batch.slice(lo, 256)
                lists = shingle_lists([t.as_py() or "" for name in ("text_a", "text_b") for t in part.column(name)], WIDTH)
                n = len(part)
                keep = pa.array([multiset_jaccard(lists[i], lists[n + i]) >= threshold for i in range(n)], pa.bool_())
                yield pa.RecordBatch.from_arrays([part.column("a"), part.column("b")], ["a", "b"]).filter(keep)

    with_a = pairs.join(texts.toDF("a", "ha", "text_a"), ["a", "ha"])
    with_b = with_a.join(texts.toDF("b", "hb", "text_b"), ["b", "hb"])
    return with_b.select("a", "b", "text_a", "text_b").mapInArrow(run, "a bigint, b bigint")


def near_duplicates(documents: DataFrame, *, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, component) of every document with words and an id; component is the smallest id of its class."""
    signed = shared.materialize(signature_table(documents, id_col, text_col).where("id is not null and n > 0"), "bag-signatures")
    first_of = shared.materialize(signed.groupBy("f1", "f2").agg(F.min(F.struct("id", "h")).alias("rep")).select("f1", "f2", "rep.id", "rep.h"), "bag-firsts")
    banded = (
        signed.join(first_of, ["f1", "f2", "id", "h"], "left_semi")
        .dropDuplicates(["id", "h"])
        .select("id", "h", "n", *SKETCH, *PARITIES, F.posexplode("bands").alias("band", "key"))
    )
    # a bucket of one is left out before its sketch moves
    keys = banded.groupBy("band", "key").agg(F.min(F.struct("id", "h")).alias("hub"), F.count("*").alias("members")).where("members > 1")
    in_buckets = shared.materialize(banded.select("id", "h", "band", "key").join(keys, ["band", "key"]), "bag-buckets")
    texts = documents.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(text_col).alias("h"), F.col(text_col).alias("text"))
    texts = shared.materialize(texts.join(in_buckets.select("id", "h").distinct(), ["id", "h"], "left_semi").dropDuplicates(["id", "h"]), "bag-texts")
    spokes = in_buckets.where("id <> hub.id or h <> hub.h").select(F.col("id").alias("a"), F.col("h").alias("ha"), F.col("hub.id").alias("b"), F.col("hub.h").alias("hb")).distinct()
    links = shared.materialize(_verified(spokes, texts, threshold), "bag-links")
    classes = shared.materialize(connected_components(links), "bag-classes")
    # buckets that still hold several classes: members outside of the largest against some of the largest, then those still outside against those of other classes
    placed = in_buckets.drop("members").join(classes.withColumnRenamed("node", "id"), "id", "left").withColumn("component", F.coalesce("component", "id"))
    sizes = placed.groupBy("band", "key", "component").agg(F.count("*").alias("members"))
    mixed = sizes.groupBy("band", "key").agg(F.max(F.struct("members", "component")).alias("most"), F.count("*").alias("held")).where("held > 1").select("band", "key", F.col("most.component").alias("main"))
    # a member that many others meet is near the middle of its group
    central = in_buckets.groupBy("id", "h").agg(F.sum("members").alias("central"))
    sketches = signed.select("id", "h", "n", "bands", *SKETCH, *PARITIES).dropDuplicates(["id", "h"]).join(central, ["id", "h"])
    open_ = placed.join(mixed, ["band", "key"]).join(sketches, ["id", "h"])
    place = F.row_number().over(Window.partitionBy("band", "key").orderBy(F.desc("central"), "id", "h"))
    pivots = open_.where("component = main").select("band", "key", "id", "h", "central").withColumn("place", place).where(F.col("place") <= PIVOTS)
    open_ = open_.join(pivots.select("band", "key", "id", "h", F.lit(True).alias("pivot")), ["band", "key", "id", "h"], "left").withColumn("pivot", F.coalesce("pivot", F.lit(False)))
    open_ = shared.materialize(open_, "bag-open")
    total, share = F.col("n_a") + F.col("n_b"), (1 - threshold) / (1 + threshold)
    differ = lambda names: sum((F.bit_count(F.col(c).bitwiseXOR(F.col("r" + c))) for c in names), F.lit(0))
    close = (F.col("n_a") >= threshold * F.col("n_b")) & (F.col("n_b") >= threshold * F.col("n_a"))  # bags too unequal in size can't overlap enough
    possible = close & (differ(PARITIES) <= total * share + 1e-6) & (differ(SKETCH) <= sketch_bound(threshold))
    bits = [*SKETCH, *PARITIES]
    not_hub = "not (id = hub.id and h = hub.h)"  # the hub has met all

    def across(outside: DataFrame, partners: DataFrame) -> DataFrame:
        """(a, ha, b, hb): members outside of their bucket's main class with partners of other classes that they may match."""
        left = outside.where(not_hub).select("band", "key", F.col("id").alias("a"), F.col("h").alias("ha"), F.col("n").alias("n_a"), F.col("component").alias("c_a"), "main", F.col("bands").alias("of_a"), *bits)
        right = partners.where(not_hub).select("band", "key", F.col("id").alias("b"), F.col("h").alias("hb"), F.col("n").alias("n_b"), F.col("component").alias("c_b"), F.col("bands").alias("of_b"), *[F.col(c).alias("r" + c) for c in bits])
        # a pair of several common buckets meets in the first of them
        first = F.array_position(F.zip_with("of_a", "of_b", lambda x, y: x == y), True) == F.col("band") + 1
        met = left.join(right, ["band", "key"]).where((F.col("c_a") != F.col("c_b")) & possible & first)
        one, two = F.struct(F.col("a").alias("id"), F.col("ha").alias("h")), F.struct(F.col("b").alias("id"), F.col("hb").alias("h"))
        pairs = met.select(F.least(one, two).alias("x"), F.greatest(one, two).alias("y")).distinct()
        return pairs.select(F.col("x.id").alias("a"), F.col("x.h").alias("ha"), F.col("y.id").alias("b"), F.col("y.h").alias("hb"))

    outside = open_.where("component <> main")
    to_pivots = shared.materialize(_verified(across(outside, open_.where("pivot")), texts, threshold), "bag-to-pivots")
    known = links.union(to_pivots).union(classes.select(F.col("node").alias("a"), F.col("component").alias("b")))
    merged = shared.materialize(connected_components(known), "bag-classes")
    now = lambda name: merged.select(F.col("node").alias(name), F.col("component").alias("now_" + name))
    outside = outside.join(now("component"), "component", "left").join(now("main"), "main", "left")
    outside = outside.where(F.coalesce("now_component", "component") != F.coalesce("now_main", "main"))
    more = shared.materialize(_verified(across(outside, open_.where("not pivot")), texts, threshold), "bag-more")
    # the texts of an id stand for one document
    of_id = signed.select("id", "f1", "f2").join(first_of.select("f1", "f2", F.col("id").alias("rep")), ["f1", "f2"]).select("id", "rep").distinct()
    several = of_id.groupBy("id").agg(F.min("rep").alias("r0"), F.max("rep").alias("r1")).where("r0 < r1").select("id")
    tied = of_id.join(several, "id").select(F.col("id").alias("a"), F.col("rep").alias("b"))
    classes = connected_components(more.union(tied).union(merged.select(F.col("node").alias("a"), F.col("component").alias("b"))))
    of_rep = classes.withColumnRenamed("node", "rep")
    out = shared.materialize(of_id.join(of_rep, "rep", "left").select("id", F.coalesce("component", "rep").alias("component")).distinct(), "bag-result")
    shared.discard(signed, first_of, in_buckets, texts, links, open_, to_pivots, more)
    return out


def keep_one_each(documents: DataFrame, **options) -> DataFrame:
    """``documents`` without the documents whose class holds a smaller doc_id."""
    later = near_duplicates(documents, **options).where("id <> component").select(F.col("id").alias("__later")).distinct()
    return documents.join(later, documents["doc_id"] == later["__later"], "left_anti")
