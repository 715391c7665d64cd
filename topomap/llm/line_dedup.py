"""Line dedup by an exact set-similarity join, in DataFrame functions only.

A line is the set of its words; blank lines take no part. A line is removed if an earlier line (by document, then place) has the same set or a
Jaccard of ``NUM / DEN`` or more with it. Lines of equal sets are told by a 128-bit hash. For the others, words are ordered by rarity and a
line is entered under its first ``n - ceil(t n) + 1`` words only; two lines that meet must pass the length filter, the positional filter and a
bitmap filter (bits that differ can't outnumber the words that may differ), which lose no match. Pairs left over are verified on whole sets.

Rarity is the word's count over all lines in sixteen levels, read from a counting sketch of ``CELLS`` cells: what is sent to tasks is 512 KB whatever the
input, and words that share a cell only share a level. Within a level words are ordered by hash, so the order is the same for all lines.

To know that an earlier line exists, a line is first tried against the earliest of the lines under each of its ``TRIALS`` rarest words, and these pairs are verified; only lines without
success there meet all earlier lines under their words. So members of a large group of alike lines that share a rare word cost a row per word, not a pair per pair. The bits of lines beyond 64 words are four times as many,
as such lines may differ in more words than 64 parities can tell.

Null ids, null and empty texts lose nothing. Rows that repeat an id and its text are one document; other texts of an id are documents after it, in the order of a hash. Very long lines are sets like others. An empty table gives
an empty result. Words are compared by 64 bits of hash, equal sets by 128 bits over 58 of each word.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.ordering import dense_index
from . import shared

NUM, DEN = 4, 5
#: Cells of the counting sketch, a byte each.
CELLS = 1 << 19
#: A cell's level is how many of these its count exceeds; they grow with the mean count of a cell beyond 32.
LEVELS = tuple(1 << k for k in range(15))
HASH_BITS = 58
#: A pair carries a whole set through a shuffle. Where there are more pairs than sets they are verified in parts, one after another, of about as many pairs as sets, in at most so many parts: this bounds the disk, not the pairs.
PARTS = 32
#: Longs of parities of a line; how many of its rarest words a line is first tried under; the flag of open lines in an entry.
LANES = 4
TRIALS = 3
OPEN = 1 << 62
#: Bits of the filter of documents whose lines are verified.
FILTER_BITS = 1 << 19
#: Borders of the lanes among the hashes.
MARKS = (-(1 << 62), 0, 1 << 62)


def _lines(documents: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc, line, words) of every line with words."""
    rows = documents.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc"), F.posexplode(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n")).alias("line", "raw"))
    return rows.where(F.col("raw").rlike(r"[^\x20\x09-\x0D]")).select("doc", "line", _pieces(F.col("raw")).alias("words"))


def _pieces(line: Column) -> Column:
    """The words of a line, with empty strings at its ends or where blanks meet. A split by one plain character is several times cheaper than one by a pattern, which lines with other white space take."""
    return F.when(line.rlike(r"[\x09\x0B-\x0D]"), F.split(line, shared.SPACE_RUN)).otherwise(F.split(line, " "))


def _cell(hashed: Column) -> Column:
    return hashed.bitwiseAND(F.lit(CELLS - 1)).cast("int")


def rarity_sketch(documents: DataFrame, id_col: str, text_col: str) -> Column:
    """The levels of all cells as a constant of ``CELLS`` bytes (a level and the bit 64 in each), put together before it reaches the driver."""
    lines = documents.where(F.col(id_col).isNotNull()).select(F.explode(F.split(F.col(text_col), "\n")).alias("line"))
    hashed = lines.select(F.explode(_pieces(F.col("line"))).alias("word")).where("word <> ''").select(F.xxhash64("word").alias("h"))
    counts = shared.materialize(hashed.groupBy(_cell(F.col("h")).alias("cell")).agg(F.count("*").alias("n")), "word-cells")
    unit = max(1.0, (counts.agg(F.sum("n")).first()[0] or 0) / CELLS / 32)
    level = sum(((F.col("n") > F.lit(unit * x)).cast("int") for x in LEVELS), F.lit(0))
    every = documents.sparkSession.range(CELLS).select(F.col("id").cast("int").alias("cell")).join(counts.select("cell", level.alias("level")), "cell", "left")
    blocks = every.groupBy(F.shiftright("cell", 10).alias("block")).agg(F.array_sort(F.collect_list(F.struct("cell", F.coalesce("level", F.lit(0)).alias("level")))).alias("cells"))
    texts = blocks.select("block", F.array_join(F.transform("cells", lambda c: F.char(c["level"] + 64)), "").alias("text")).collect()
    shared.discard(counts)
    return F.lit("".join(r["text"] for r in sorted(texts)).encode("ascii"))


def _hashes(words: Column) -> Column:
    """The set of a line as 64-bit hashes, in no order."""
    return F.array_remove(F.array_distinct(F.transform(words, lambda w: F.xxhash64(w))), F.xxhash64(F.lit("")))


def _ranked(h: Column, levels: Column) -> Column:
    """Level, then hash. The bit 64 of the sketch's byte is shifted out."""
    level = F.ascii(F.substring(levels, _cell(h) + 1, F.lit(1)).cast("string"))
    return F.shiftleft(level.cast("long"), HASH_BITS).bitwiseOR(h.bitwiseAND(F.lit((1 << HASH_BITS) - 1)))


def _may_be_in(values: DataFrame):
    """A test for values of the one column of ``values``, which lets all of them through and few others: a Bloom filter of one hash and of 128 KB, whatever their number."""
    cell = lambda v: F.pmod(F.xxhash64(v), F.lit(FILTER_BITS)).cast("long")
    at = cell(values[values.columns[0]]) + 1
    rows = values.groupBy(F.bitmap_bucket_number(at).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits")).collect()
    whole = np.zeros(FILTER_BITS // 8, np.uint8)
    for r in rows:
        whole[(r["bucket"] - 1) * 4096 :][:4096] = np.frombuffer(r["bits"], np.uint8)
    # four bits a character, so that it is ASCII
    text = F.lit((np.stack([whole & 15, whole >> 4], 1).ravel() + 64).tobytes())

    def may_be_in(value: Column) -> Column:
        four = F.ascii(F.substring(text, F.shiftright(cell(value), 2).cast("int") + 1, F.lit(1)).cast("string"))
        return F.call_function("shiftright", four, F.pmod(cell(value), F.lit(4)).cast("int")).bitwiseAND(F.lit(1)) == 1

    return may_be_in


def _ceil_share(n: Column) -> Column:
    """ceil(t * n) in integers."""
    return F.floor((NUM * n + (DEN - 1)) / DEN).cast("int")


def _needed(n: Column, m: Column) -> Column:
    """Smallest overlap of two sets of n and m words that reaches the threshold."""
    return F.floor((NUM * (n + m) + (NUM + DEN - 1)) / (NUM + DEN)).cast("int")


def _may_match(n: Column, i: Column, bits: Column, m: Column, j: Column, bits2: Column) -> Column:
    length = (DEN * m >= NUM * n) & (DEN * n >= NUM * m)
    position = F.least(n - i, m - j) >= _needed(n, m)
    return length & position & (_apart(n, bits, m, bits2) <= n + m - 2 * _needed(n, m))


def _apart(n: Column, bits: Column, m: Column, bits2: Column) -> Column:
    """How many parities differ, at least: of all lanes if both lines are long, of the folded lanes otherwise."""
    differ = [bits[k].bitwiseXOR(bits2[k]) for k in range(LANES)]
    return F.when(F.least(n, m) > 64, reduce(Column.__add__, map(F.bit_count, differ))).otherwise(F.bit_count(reduce(Column.bitwiseXOR, differ)))


def _parities(hashes: Column) -> Column:
    """64 bits: which residues modulo 64 an odd number of the hashes have. Words that two lines share cancel, so what differs tells of the others alone."""
    return F.aggregate(hashes, F.lit(0).cast("long"), lambda s, t: s.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), t.bitwiseAND(F.lit(63)).cast("int"))))


def _marked(hashes: Column) -> Column:
    """The hashes in order, with the borders of the lanes among them."""
    return F.sort_array(F.concat(hashes, F.array(*[F.lit(x).cast("long") for x in MARKS])))


def _ends(marked: Column) -> list[Column]:
    return [F.array_position(marked, F.lit(x).cast("long")).cast("int") for x in MARKS]


def _lanes(marked: Column, ends: list[Column]) -> list[Column]:
    """Parities of each lane."""
    ends = [F.lit(0), *ends, F.size(marked) + 1]
    return [_parities(F.slice(marked, x + 1, y - x - 1)) for x, y in zip(ends, ends[1:])]


def _folded(n: Column, lanes: list[Column]) -> list[Column]:
    """Up to 64 words the first lane holds all. Longer lines, which may differ in more words, have a lane for each quarter of the hashes' range."""
    one = reduce(Column.bitwiseXOR, lanes)
    return [F.when(n > 64, lane).otherwise(F.lit(0).cast("long") if k else one) for k, lane in enumerate(lanes)]


def _bitmap(hashes: Column) -> Column:
    """The parities of a line in ``LANES`` longs."""
    marked = _marked(hashes)
    return F.array(*_folded(F.size(hashes), _lanes(marked, _ends(marked))))


def removed_lines(documents: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc, h, lines): for each document that loses lines, the places of the lines it loses; h, where it isn't null, is the hash of the text that is meant."""
    doc, h = F.col(id_col).cast("long"), F.xxhash64(text_col)
    lines = F.size(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n"))
    known = documents.where(doc.isNotNull()).select(doc.alias("doc"), h.alias("h"), lines.alias("lines"))
    by_id = known.groupBy("doc").agg(F.min("h").alias("h0"), F.max("h").alias("h1"), F.max("lines").alias("lines"))
    low, high, most, clash = by_id.agg(F.min("doc"), F.max("doc"), F.max("lines"), F.max(F.col("h0") != F.col("h1"))).first()
    room = 63 - max(1, int(most or 0).bit_length())
    if low is None or not clash and -(1 << room) <= low and high < 1 << room:
        return _removed(documents, id_col, text_col).select("doc", F.lit(None).cast("long").alias("h"), "lines")
    # ids that leave no room for the line in a long, or that stand for several texts, give way to the places of (id, text) in order
    numbers = shared.materialize(dense_index(known.select("doc", "h").distinct(), ["doc", "h"], "number"), "line-numbers")
    placed = documents.select(doc.alias("doc"), h.alias("h"), F.col(text_col).alias("text")).join(numbers, ["doc", "h"]).select("number", "text")
    gone = _removed(placed, "number", "text").withColumnRenamed("doc", "number")
    return gone.join(numbers, "number").select("doc", "h", "lines")


def _removed(documents: DataFrame, id_col: str, text_col: str) -> DataFrame:
    levels = rarity_sketch(documents, id_col, text_col)
    c, lanes = F.col, [f"bits{k}" for k in range(LANES)]
    sets = _lines(documents, id_col, text_col).select("doc", "line", _hashes(c("words")).alias("hashes"))
    # in steps, so that no part is made twice
    ends = [f"end{k}" for k in range(LANES - 1)]
    sets = sets.select("doc", "line", "hashes", _marked(c("hashes")).alias("marked"))
    sets = sets.select("*", *[x.alias(e) for e, x in zip(ends, _ends(c("marked")))])
    n, tokens = F.size("tokens"), F.sort_array(F.transform("hashes", lambda h: _ranked(h, levels)))
    sets = sets.select("doc", "line", tokens.alias("tokens"), *[x.alias(k) for k, x in zip(lanes, _lanes(c("marked"), [c(e) for e in ends]))])
    sets = sets.select(
        "doc", "line", n.alias("n"), F.xxhash64("tokens").alias("f1"), F.xxhash64(F.lit(1), "tokens").alias("f2"),
        *[x.alias(k) for k, x in zip(lanes, _folded(n, [c(k) for k in lanes]))],
        F.slice("tokens", 1, n - _ceil_share(n) + 1).alias("prefix"),
    )
    sets = shared.materialize(sets, "line-sets")
    most = sets.agg(F.max("line")).first()[0]
    shift = max(1, int(most or 0).bit_length())
    keyed = sets.select(F.shiftleft("doc", shift).bitwiseOR(c("line").cast("long")).alias("id"), "n", "f1", "f2", *lanes, "prefix")
    firsts = keyed.groupBy("f1", "f2").agg(F.min("id").alias("first"))
    # one line of each set goes on
    repeated = c("id") != c("first")
    placed = shared.materialize(keyed.join(firsts, ["f1", "f2"]).select("id", "n", repeated.alias("repeated"), *lanes, F.when(~repeated, c("prefix")).alias("prefix")), "line-placed")
    shared.discard(sets)
    repeats = shared.materialize(placed.where("repeated").select("id"), "line-repeats")
    single = placed.where("not repeated").drop("repeated")

    def may_match(x: str, y: str) -> Column:
        bits, bits2 = (F.array(*[c(f"{side}.{lane}") for lane in lanes]) for side in (x, y))
        return _may_match(_length(c(f"{x}.at")), _place(c(f"{x}.at")), bits, _length(c(f"{y}.at")), _place(c(f"{y}.at")), bits2)

    def verified(pairs: DataFrame) -> DataFrame:
        ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
        # a document comes once, with the places of its lines that are wanted: no other line moves
        wanted = ids.groupBy(F.shiftright("id", shift).alias("owner")).agg(F.collect_list(c("id").bitwiseAND(F.lit((1 << shift) - 1)).cast("int")).alias("places"))
        may_hold = _may_be_in(ids.select(F.shiftright("id", shift)))
        held = documents.select(c(id_col).cast("long").alias("owner"), c(text_col).alias("text")).where(may_hold(c("owner"))).join(wanted, "owner")
        # exploding an array of one keeps Catalyst from splitting the text again for every place
        split = held.select("owner", "places", F.explode(F.array(F.split("text", "\n"))).alias("raws"))
        again = split.select("owner", F.explode(F.transform("places", lambda p: F.struct(p.alias("line"), F.get("raws", p).alias("raw")))).alias("l"))
        again = again.select(F.shiftleft("owner", shift).bitwiseOR(c("l.line").cast("long")).alias("id"), _pieces(c("l.raw")).alias("words"))
        tokens = shared.materialize(again.select("id", _hashes(c("words")).alias("tokens")), "line-tokens")
        enough = F.size(F.array_intersect("x", "y")) >= _needed(F.size("x"), F.size("y"))
        found, parts = [], min(PARTS, -(-pairs.count() // max(1, tokens.count())) or 1)
        for k in range(parts):
            part = pairs.where(F.pmod(F.xxhash64("a"), F.lit(parts)) == k)
            both = part.join(tokens.toDF("a", "x"), "a").join(tokens.toDF("b", "y"), "b")
            found.append(shared.materialize(both.where(enough).select("a"), "line-matches"))
        shared.discard(tokens)
        return reduce(DataFrame.union, found)

    # first the trials: under each of its rarest words, a line meets the earliest line of that word
    tops = _entries(single, F.lit(True), F.slice("prefix", 1, TRIALS), lanes)
    hub = F.first(F.struct("id", "at", *lanes)).over(Window.partitionBy("token").orderBy("id"))
    tops = tops.select(F.struct("id", "at", *lanes).alias("x"), hub.alias("y")).where(c("y.id") < c("x.id"))
    trials = shared.materialize(tops.where(may_match("x", "y")).select(c("x.id").alias("a"), c("y.id").alias("b")).distinct(), "line-trials")
    settled = shared.materialize(verified(trials).distinct(), "line-settled")
    # then all pairs of lines that are still open with earlier lines
    is_open = c("a").isNull()
    lines = shared.materialize(single.join(settled, c("id") == c("a"), "left").select("id", "n", *lanes, "prefix", is_open.alias("open")), "line-open")
    shared.discard(placed)
    # a word that stands in a third of the lines is in the prefix only of lines of such words alone, so rarity bounds the groups of this join;
    # the window keeps the filter of open lines above the exchange, which both sides share
    entries = _entries(lines, c("open"), c("prefix"), lanes)
    later = entries.withColumn("place", F.row_number().over(Window.partitionBy("token").orderBy("id"))).where((c("place") > 1) & (c("at") >= OPEN))
    pairs = later.alias("x").join(entries.alias("y"), (c("x.token") == c("y.token")) & (c("y.id") < c("x.id")) & may_match("x", "y"))
    pairs = pairs.select(c("x.id").alias("a"), c("y.id").alias("b")).distinct().join(trials, ["a", "b"], "left_anti")
    pairs = shared.materialize(pairs, "line-pairs")
    shared.discard(lines, trials)
    gone = repeats.union(settled.select("a"))
    if not pairs.isEmpty():
        # one line that is alike is enough, so each part of the pairs is verified whole and no pair twice
        gone = gone.union(verified(pairs))
    shared.discard(pairs)
    return gone.select(F.shiftright("id", shift).alias("doc"), c("id").bitwiseAND(F.lit((1 << shift) - 1)).cast("int").alias("line")).groupBy("doc").agg(F.collect_set("line").alias("lines"))


def _entries(lines: DataFrame, is_open: Column, words: Column, lanes: list[str]) -> DataFrame:
    """(token, id, at, lanes): a row per line and word; ``at`` holds the flag, the line's length and the word's place. No column is null, which tells Catalyst that it needs no filters of its own."""
    rows = lines.select("id", is_open.alias("open"), "n", *lanes, F.posexplode(words).alias("i", "token"))
    at = F.shiftleft(F.col("open").cast("long"), 62).bitwiseOR(F.shiftleft(F.col("n").cast("long"), 31)).bitwiseOR(F.col("i").cast("long"))
    filled = {"token": F.col("token"), "id": F.col("id"), "at": at} | {x: F.col(x) for x in lanes}
    return rows.select(*[F.coalesce(v, F.lit(0).cast("long")).alias(k) for k, v in filled.items()])


def _length(at: Column) -> Column:
    return F.shiftright(at, 31).bitwiseAND(F.lit((1 << 31) - 1)).cast("int")


def _place(at: Column) -> Column:
    return at.bitwiseAND(F.lit((1 << 31) - 1)).cast("int")


def _kept(text: Column, lines: Column) -> Column:
    all_lines = F.split(text, "\n")
    return F.when(lines.isNull(), text).otherwise(F.array_join(F.filter(all_lines, lambda x, i: ~F.array_contains(lines, i)), "\n"))


def line_report(documents: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, n_lines (with words), n_removed, kept_sha256 per row."""
    gone = removed_lines(documents, id_col=id_col, text_col=text_col)
    data = documents.select(F.col(id_col).alias("id"), F.xxhash64(text_col).alias("own"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    data = data.join(gone, (F.col("id") == F.col("doc")) & (F.col("h").isNull() | (F.col("h") == F.col("own"))), "left")
    worded = F.size(F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))).cast("long")
    removed = F.when(F.col("lines").isNull(), 0).otherwise(F.size("lines")).cast("long")
    return data.select(F.col("id").alias(id_col), worded.alias("n_lines"), removed.alias("n_removed"), F.sha2(F.encode(_kept(F.col("text"), F.col("lines")), "UTF-8"), 256).alias("kept_sha256"))


def drop_repeated_lines(documents: DataFrame) -> DataFrame:
    """``documents`` with the texts that are left, n_chars following; a document that loses all its words goes."""
    gone = removed_lines(documents).select(F.col("doc").alias("__doc"), F.col("h").alias("__h"), F.col("lines").alias("__lines"))
    same_text = F.col("__h").isNull() | (F.col("__h") == F.xxhash64(documents["text"]))
    joined = documents.join(gone, (documents["doc_id"] == gone["__doc"]) & same_text, "left").withColumn("text", _kept(F.col("text"), F.col("__lines")))
    left = joined.where(F.col("__lines").isNull() | F.col("text").rlike(r"[^\x20\x09-\x0D]"))
    if "n_chars" in documents.columns:
        left = left.withColumn("n_chars", F.when(F.col("__lines").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(documents.schema["n_chars"].dataType)))
    return left.select(documents.columns)
