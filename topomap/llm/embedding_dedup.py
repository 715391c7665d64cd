"""Embedding near-dedup: cross-polytope hashing after fast Hadamard rotations, multiprobe buckets, verified pairs.

Vectors of one label and length are compared by cosine in double precision. Equal vectors of a label are one representative with a count. A table's bucket is,
for each of K rotations (three rounds of random signs and a fast Hadamard transform), the coordinate of largest size and its sign;
besides its own bucket a vector probes those that take a runner-up coordinate in one rotation, or in two. K grows with the largest label, so that
buckets stay small, and the number of tables with K. Candidates must agree in most of 128 sign bits (a bound six deviations wide at the threshold) before
their cosine is computed, so unlike vectors that share a bucket don't become rows. Sign bits of short vectors depend on each other, so these have no such filter.

Null, empty and zero vectors, vectors with null or non-finite components, and rows with a null label or id, link with nothing: they have
0 links and are kept as their own component. An empty table gives an empty result. Equal rows count as different vectors.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared
from .components import connected_components

SEED = 20240229
TABLES = 12
#: Vectors of fewer components are padded to so many, and their candidates go straight to the cosine.
SHORT = 16


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of the rows; their length is a power of two."""
    n, d = x.shape
    step = 1
    while step < d:
        pair = x.reshape(n, d // (2 * step), 2, step)
        x = np.concatenate((pair[:, :, :1] + pair[:, :, 1:], pair[:, :, :1] - pair[:, :, 1:]), axis=2).reshape(n, d)
        step *= 2
    return x / math.sqrt(d)


def padded_length(dim: int) -> int:
    """A power of two, and no less than ``SHORT``: rotations of fewer coordinates repeat a few directions."""
    return max(SHORT, 1 << max(1, (dim - 1).bit_length()))


def rotations(dim: int, count: int) -> np.ndarray:
    """Signs of ``count`` rotations: count x 3 x padded dim."""
    return np.random.Generator(np.random.PCG64(SEED + dim)).choice(np.array([-1.0, 1.0]), size=(count, 3, padded_length(dim)))


def rotate(x: np.ndarray, signs: np.ndarray) -> np.ndarray:
    out = np.zeros((len(x), signs.shape[-1]))
    out[:, : x.shape[1]] = x
    for s in signs:
        out = hadamard(out * s)
    return out


def buckets_of(x: np.ndarray, signs: np.ndarray, tables: int, k: int, probes: bool) -> np.ndarray:
    """n x tables x (1 or 1 + probes) bucket numbers; the first is a vector's own."""
    base = 2 * signs.shape[-1]
    tops = np.empty((len(x), tables * k, 3), np.int64)
    for f in range(tables * k):
        r = rotate(x, signs[f])
        top = np.argpartition(-np.abs(r), 2, axis=1)[:, :3]
        order = np.argsort(-np.abs(np.take_along_axis(r, top, 1)), axis=1, kind="stable")
        top = np.take_along_axis(top, order, 1)
        tops[:, f] = 2 * top + (np.take_along_axis(r, top, 1) < 0)
    tops = tops.reshape(len(x), tables, k, 3)
    scale = base ** np.arange(k, dtype=np.int64)
    own = (tops[:, :, :, 0] * scale).sum(axis=2)
    if not probes:
        return own[:, :, None]
    out = [own]
    change = lambda f, c: (tops[:, :, f, c] - tops[:, :, f, 0]) * scale[f]
    out += [own + change(f, c) for f in range(k) for c in (1, 2)]
    out += [own + change(f, 1) + change(g, 1) for f in range(k) for g in range(f)]
    return np.stack(out, axis=2)


def sign_bits(x: np.ndarray, signs: np.ndarray) -> np.ndarray:
    """n x 2 words of 64 sign bits, from coordinates of the last rotations."""
    bits = np.concatenate([rotate(x, s) > 0 for s in signs], axis=1)
    return np.packbits(bits[:, :128], axis=1).view(np.int64)


def sign_bound(threshold: float) -> int:
    """Bits of 128 in which a pair at the threshold may differ: six deviations above the mean."""
    p = math.acos(threshold) / math.pi
    return math.ceil(128 * p + 6 * math.sqrt(128 * p * (1 - p)))


def linked_vectors(embeddings: DataFrame, *, threshold: float = 0.93, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """``id_col``, n_links, component_id, kept for every row."""
    x = F.col(vector_col).cast("array<double>")
    data = embeddings.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).alias("label"), x.alias("x"))
    data = data.withColumn("usable", F.coalesce(_usable(), F.lit(False)))
    data = data.withColumn("f1", F.xxhash64("label", "x")).withColumn("f2", F.xxhash64(F.lit(1), "label", "x"))
    firsts = shared.materialize(
        data.where("usable").groupBy("f1", "f2").agg(F.min("id").alias("rep"), F.count("*").alias("copies"), F.first("label").alias("label"), F.first("x").alias("x")), "vector-firsts"
    )
    largest = firsts.groupBy("label", F.size("x").alias("dim")).count().agg(F.max("count"), F.max("dim")).first()
    if largest[0] is None:
        return embeddings.select(F.col(id_col), F.lit(0).cast("long").alias("n_links"), F.col(id_col).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    k = max(1, math.ceil(math.log(max(2, largest[0])) / math.log(2 * padded_length(int(largest[1])))))
    tables = TABLES * 2 ** max(0, k - 2)

    def hashed(probes: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                lists = batch.column("x")
                sizes = lists.value_lengths().to_numpy()
                for dim in np.unique(sizes).tolist():
                    rows = np.flatnonzero(sizes == dim)
                    for lo in range(0, len(rows), 1000):
                        part = batch.take(pa.array(rows[lo : lo + 1000]))
                        x = part.column("x").flatten().to_numpy().reshape(-1, dim)
                        x = x / np.abs(x).max(axis=1, keepdims=True)
                        signs = rotations(dim, tables * k + -(-128 // padded_length(dim)))
                        b = buckets_of(x, signs, tables, k, probes)
                        bits = sign_bits(x, signs[tables * k :]) if dim >= SHORT else np.zeros((len(x), 2), np.int64)
                        n, t, p = b.shape
                        who = np.repeat(np.arange(n), t * p)
                        table = np.tile(np.repeat(np.arange(t), p), n).astype(np.int32)
                        yield pa.RecordBatch.from_arrays(
                            [part.column("label").take(pa.array(who)), pa.array(np.full(len(who), dim, np.int32)), pa.array(table), pa.array(b.ravel()), part.column("rep").take(pa.array(who)), pa.array(bits[who, 0]), pa.array(bits[who, 1])],
                            ["label", "dim", "tab", "bucket", "rep", "s1", "s2"],
                        )

        return run

    kind = firsts.schema["label"].dataType.simpleString()
    schema = f"label {kind}, dim int, tab int, bucket bigint, rep bigint, s1 bigint, s2 bigint"
    vectors = firsts.select("rep", "label", "x")
    own = vectors.mapInArrow(hashed(False), schema).withColumnsRenamed({"rep": "b", "s1": "b1", "s2": "b2"})
    probe = vectors.mapInArrow(hashed(True), schema).withColumnRenamed("rep", "a")
    apart = F.bit_count(F.col("s1").bitwiseXOR(F.col("b1"))) + F.bit_count(F.col("s2").bitwiseXOR(F.col("b2")))
    found = probe.join(own, ["label", "dim", "tab", "bucket"]).where((F.col("a") != F.col("b")) & (apart <= sign_bound(threshold)))
    pairs = found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = batch.column("xa").value_lengths().to_numpy()
            keep = np.zeros(len(batch), bool)
            for dim in np.unique(sizes).tolist():
                rows = np.flatnonzero(sizes == dim)
                x, y = (batch.column(c).take(pa.array(rows)).flatten().to_numpy().reshape(-1, dim) for c in ("xa", "xb"))
                keep[rows] = np.einsum("ij,ij->i", x, y) / np.sqrt(np.einsum("ij,ij->i", x, x) * np.einsum("ij,ij->i", y, y)) >= threshold
            yield batch.select(["a", "b"]).filter(pa.array(keep))

    x_of = lambda c: vectors.select(F.col("rep").alias(c), F.col("x").alias("x" + c))
    links = shared.materialize(pairs.join(x_of("a"), "a").join(x_of("b"), "b").mapInArrow(verify, "a bigint, b bigint"), "vector-links")
    classes = connected_components(links)
    both = links.union(links.select("b", "a")).toDF("rep", "other")
    linked = both.join(firsts.select(F.col("rep").alias("other"), "copies"), "other").groupBy("rep").agg(F.sum("copies").alias("others"))
    per_first = firsts.select("f1", "f2", "rep", "copies").join(linked, "rep", "left").join(classes.withColumnRenamed("node", "rep"), "rep", "left")
    per_first = per_first.select("f1", "f2", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("component", "rep").alias("component"))
    rows = data.select("id", "usable", F.when(F.col("usable"), F.col("f1")).alias("f1"), F.when(F.col("usable"), F.col("f2")).alias("f2")).join(per_first, ["f1", "f2"], "left")
    component = F.coalesce("component", "id")
    return rows.select(F.col("id").alias(id_col), F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(True)).alias("kept"))


def _usable():
    """Rows that can link: id, label, and a vector of finite components that isn't zero."""
    finite = F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    return F.col("id").isNotNull() & F.col("label").isNotNull() & F.col("x").isNotNull() & finite & F.exists("x", lambda v: v != 0)
