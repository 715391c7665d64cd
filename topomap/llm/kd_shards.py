"""Shards by k-d tree partitioning, in DataFrame functions only.

A node that is to hold several shards is split along its widest dimension (extent over the root's extent) at the weighted median,
until a leaf is one shard. Medians of all nodes of a level are found together and exactly: a round sums weights
in ``BUCKETS`` equal buckets of each node's interval and keeps the bucket that holds the goal, until it is one value. Rows
equal in the dimension are split by the content key and at last by a hash of the id, but only where the cut at the group's border
would miss the goal by more than ``TOLERANCE`` of the node; so equal contents mostly stay together and sizes stay near equal whatever is hot.

The driver holds the tree (one node per shard) and at most nodes x BUCKETS sums. Rows aren't shuffled for splitting; slots are
numbered in sub-groups of a shard and shifted by the sub-groups' counts, so no task holds a whole shard.

Null texts weigh 1 and have no content key in the result. Null ids, repeated rows and ties are dealt like others; rows equal in every key stay together. An
empty table gives no rows. Columns of the input with clashing names are not read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import shared

BUCKETS = 1024
TOLERANCE = 0.005


@dataclass
class Node:
    """A box of the tree: how many shards it holds, the first of them, and, once split, where."""

    shards: int
    first: int
    cuts: list[tuple[str, int]] | None = None  # left of it: key < cut; all but the last cut: or equal and left of the next
    low: Node | None = None
    high: Node | None = None

    def goes_low(self) -> Column:
        cond = F.lit(False)
        for key, cut in reversed(self.cuts):
            cond = (F.col(key) < cut) | ((F.col(key) == cut) & cond)
        return cond

    def leaf(self) -> Column:
        return F.lit(self.first) if self.cuts is None else F.when(self.goes_low(), self.low.leaf()).otherwise(self.high.leaf())

    def open(self) -> list[Node]:
        if self.cuts is not None:
            return self.low.open() + self.high.open()
        return [self] if self.shards > 1 else []


def _by_node(nodes: list[Node], of) -> Column:
    """A column that differs by node, for rows that carry the node's first shard as ``node``."""
    out = F.lit(None)
    for k, n in enumerate(nodes):
        out = F.when(F.col("node") == n.first, of(k)).otherwise(out)
    return out


def grow_tree(points: DataFrame, dims: list[str], shards: int) -> Node:
    """``points``: weight, content, identity and the ``dims``, all longs without nulls."""
    root = Node(shards, 0)
    scale: dict[str, float] = {}
    while nodes := root.open():
        wanted = [n.first for n in nodes]
        at = points.withColumn("node", root.leaf()).where(F.col("node").isin(wanted))
        sums = [f(c).alias(f"{name}_{c}") for c in (*dims, "content", "identity") for name, f in (("min", F.min), ("max", F.max))]
        extents = {r["node"]: r for r in at.groupBy("node").agg(F.sum("weight").alias("weight"), *sums).collect()}
        if not scale:
            scale = {d: max(1.0, float(extents[0][f"max_{d}"] - extents[0][f"min_{d}"])) if 0 in extents else 1.0 for d in dims}
        searches = []
        for n in nodes:
            e = extents.get(n.first)
            if e is None:  # an empty box: any cut will do
                n.cuts = [("content", 0)]
                continue
            widest = max(dims, key=lambda d: (e[f"max_{d}"] - e[f"min_{d}"]) / scale[d])
            goal = e["weight"] * (n.shards // 2) / n.shards
            searches.append(_Search(n, [widest, "content", "identity"], e, goal))
        while active := [s for s in searches if not s.done]:
            owners = [s.node for s in active]
            key = _by_node(owners, lambda k: F.col(active[k].key))
            inside = F.coalesce(_by_node(owners, lambda k: active[k].inside()), F.lit(False))
            bucket = ((key - _by_node(owners, lambda k: F.lit(active[k].lo))) / _by_node(owners, lambda k: F.lit(active[k].step))).cast("int")
            found = at.where(inside).groupBy("node", bucket.alias("bucket")).agg(F.sum("weight").alias("weight")).collect()
            for s in active:
                s.narrow(sorted((r["bucket"], r["weight"]) for r in found if r["node"] == s.node.first))
        for n in nodes:
            half = n.shards // 2
            n.low, n.high = Node(half, n.first), Node(n.shards - half, n.first + half)
    return root


class _Search:
    """Looks for the cut of one node, key after key."""

    def __init__(self, node: Node, keys: list[str], extent, goal: float):
        self.node, self.keys, self.extent, self.goal = node, keys, extent, goal
        self.allowed = TOLERANCE * extent["weight"]
        self.fixed: list[tuple[str, int]] = []
        self.done = False
        self._start(0.0)

    def _start(self, below: float) -> None:
        self.key, self.below = self.keys[0], below
        self.lo, self.hi = self.extent[f"min_{self.key}"], self.extent[f"max_{self.key}"]
        self.step = 1 << max(0, math.ceil(math.log2((self.hi - self.lo + 1) / BUCKETS))) if self.hi - self.lo >= BUCKETS else 1

    def inside(self) -> Column:
        cond = (F.col(self.key) >= self.lo) & (F.col(self.key) <= self.hi)
        for key, value in self.fixed:
            cond &= F.col(key) == value
        return cond

    def narrow(self, sums: list[tuple[int, int]]) -> None:
        below = self.below
        for bucket, weight in sums:
            if below + weight >= self.goal or bucket == sums[-1][0]:
                break
            below += weight
        self.lo += bucket * self.step
        self.below = below
        if self.step > 1:
            self.hi = min(self.hi, self.lo + self.step - 1)
            self.step = max(1, self.step // BUCKETS)
            return
        under, over = abs(self.goal - below), abs(below + weight - self.goal)
        if min(under, over) <= self.allowed or len(self.keys) == 1:
            self.node.cuts = [*self.fixed, (self.key, self.lo + (over < under))]
            self.done = True
            return
        self.fixed.append((self.key, self.lo))
        self.keys = self.keys[1:]
        self._start(below)


def shard_documents(documents: DataFrame, *, shards: int | None = None, target_bytes: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, size, text_crc32, shard, slot: ``shards`` of them, or as many as leaves of ``target_bytes`` need.

    Dimensions are what the text itself tells (size, lines, content key), so that equal texts are one point.
    """
    text = F.col(text_col)
    raw = F.coalesce(text, F.lit(""))
    crc = F.crc32(F.encode(raw, "UTF-8"))
    lines = F.length(raw) - F.length(F.replace(raw, F.lit("\n"), F.lit("")))
    points = documents.select(
        F.col(id_col).alias("id"), (F.octet_length(raw) + 1).cast("long").alias("weight"), crc.cast("long").alias("content"), lines.cast("long").alias("lines"), text.isNull().alias("absent")
    )
    points = points.withColumn("identity", F.xxhash64("id", "content").bitwiseAND(F.lit((1 << 31) - 1))).withColumn("size", F.col("weight"))
    points = shared.materialize(points, "shard-points")
    total = points.agg(F.count("*").alias("n"), F.coalesce(F.sum("weight"), F.lit(0)).alias("w")).first()
    shards = shards or max(1, math.ceil(total["w"] / target_bytes))
    tree = grow_tree(points, ["size", "lines", "content"], shards)
    groups = max(8, math.ceil(total["n"] / (shards * 20_000)))
    placed = points.withColumn("shard", tree.leaf().cast("int")).withColumn("part", F.pmod(F.xxhash64("identity", "id"), F.lit(groups)).cast("int"))
    counts = placed.groupBy("shard", "part").agg(F.count("*").alias("rows"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("shard", "part", F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("offset"))
    within = F.row_number().over(Window.partitionBy("shard", "part").orderBy("identity", "id", "content", "weight")) - 1
    numbered = placed.withColumn("within", within).join(offsets, ["shard", "part"])
    return numbered.select(F.col("id").alias(id_col), "size", F.when(~F.col("absent"), F.col("content")).alias("text_crc32"), "shard", (F.col("offset") + F.col("within")).alias("slot"))
