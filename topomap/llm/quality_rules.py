"""Quality by weak supervision, in DataFrame functions only.

Rules read per-document features and vote good (1), bad (-1) or abstain (0). Votes of equal pattern are counted
(at most 3 ** rules patterns, so what is gathered is bounded by the rules, not by the documents), and
expectation-maximisation over the counted patterns estimates how many of a rule's bad votes are false: those on documents
that the other rules speak for as often as for good ones. A document is kept if it passes the base limits and its posterior
probability of being good reaches the threshold, so the bad vote of a noisy rule can be outweighed.

Null and blank texts have no words, fail the base limits and are not kept. Equal rows get equal results. In an empty table there is
nothing to fit and nothing comes out. Windows of five words are found by hash and sorted inside the row, so a very long
text costs n log n in its own row. Feature columns of ``documents`` with clashing names are not read.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import shared

WINDOW = 5
SYMBOLS = "[#*$%&|<>]"




def text_features(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(``keep`` columns, id, features) per row: one projection chain without a shuffle."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    # each step is referred to several times by the next, so that Catalyst doesn't inline it
    df = documents.select(*[F.col(c) for c in keep], F.col(id_col).alias("__id"), text.alias("__text"))
    df = df.withColumn("__words", shared.words(F.col("__text"))).withColumn("__lines", F.filter(F.split("__text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    df = df.withColumn("__hashes", F.transform("__words", lambda w: F.xxhash64(w))).withColumn("n_words", F.size("__words").cast("long"))
    df = df.withColumn(
        "__windows",
        F.when(
            F.col("n_words") >= WINDOW,
            F.transform(F.sequence(F.lit(0), (F.col("n_words") - WINDOW).cast("int")), lambda i: F.xxhash64(*[F.get("__hashes", i + k) for k in range(WINDOW)])),
        ).otherwise(F.array().cast("array<bigint>")),
    ).withColumn("__repeats", F.size(F.array_distinct("__windows")) < F.size("__windows"))
    # only where some window repeats: starts of repeating windows in order, then the words they cover
    tagged = F.array_sort(F.transform("__windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn("__sorted", F.when(F.col("__repeats"), tagged))
    twin = lambda x, i: (x["h"] == F.get(F.col("__sorted"), i - 1)["h"]) | (x["h"] == F.get(F.col("__sorted"), i + 1)["h"])
    df = df.withColumn("__starts", F.sort_array(F.transform(F.filter("__sorted", lambda x, i: F.coalesce(twin(x, i), F.lit(False))), lambda x: x["i"])))
    covered = F.aggregate(
        "__starts",
        F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(-WINDOW).alias("last")),
        lambda s, i: F.struct((s["n"] + F.least(F.lit(WINDOW), i - s["last"])).alias("n"), i.alias("last")),
        lambda s: s["n"],
    )
    count = lambda pattern: F.regexp_count("__text", F.lit(pattern)).cast("long")
    return df.select(
        *keep,
        F.col("__id").alias(id_col),
        "n_words",
        F.length(F.array_join("__words", "")).cast("long").alias("word_chars"),
        count(SYMBOLS).alias("n_symbols"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("n_dup_lines"),
        F.when(F.col("__repeats"), covered).otherwise(F.lit(0)).cast("long").alias("n_repeat_words"),
        F.size("__lines").cast("long").alias("n_lines"),
        count(r"\p{Lu}").alias("n_upper"),
        count(r"[!?.,;:]{2}").alias("n_shouts"),
        count(r"\p{N}").alias("n_digits"),
        count(r"[.!?](?=[\x20\x09-\x0D]|$)").alias("n_stops"),
    )


@dataclass(frozen=True)
class Rule:
    """Votes bad where ``bad`` holds, else good where ``good`` holds, else abstains."""

    name: str
    bad: Callable[[], Column]
    good: Callable[[], Column]

    def vote(self) -> Column:
        return F.when(self.bad(), -1).when(self.good(), 1).otherwise(0)


def _share(top: str, bottom: str) -> Column:
    return F.when(F.col(bottom) > 0, F.col(top) / F.col(bottom)).otherwise(F.lit(0.0))


def _never() -> Column:
    return F.lit(False)


#: Only two rules speak for a document; the others speak against it or abstain.
RULES = (
    Rule("repetition", lambda: _share("n_repeat_words", "n_words") > 0.18, lambda: _share("n_repeat_words", "n_words") <= 0.03),
    Rule("sentences", lambda: (F.col("n_stops") == 0) & (F.col("n_words") > 60), lambda: _share("n_stops", "n_words").between(0.02, 0.34)),
    Rule("equal_lines", lambda: _share("n_dup_lines", "n_lines") > 0.4, _never),
    Rule("symbols", lambda: _share("n_symbols", "word_chars") > 0.02, _never),
    Rule("word_length", lambda: ~_share("word_chars", "n_words").between(2.0, 14.0), _never),
    Rule("capitals", lambda: _share("n_upper", "word_chars") > 0.3, _never),
    Rule("shouting", lambda: _share("n_shouts", "n_words") > 0.15, _never),
    Rule("digits", lambda: _share("n_digits", "word_chars") > 0.25, _never),
    Rule("length", lambda: F.col("n_words") < 10, _never),
)

#: Sound elsewhere, of a document and a rule: every other rule that can speak for it does. A rule's junk is so at most this many times as often as good
#: documents are, or its bad votes count as chance. That alone keeps good documents and junk apart; accuracies have no other bounds.
APART = 0.8
#: A rule has so many true bad votes beforehand, so that a handful of votes doesn't condemn it, and at the start so large a share of false ones.
TRUST = 10.0
DOUBT = 0.2


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def _votes(rules: tuple[Rule, ...]) -> Column:
    return F.array(*[r.vote() for r in rules])


def _others(rules: tuple[Rule, ...], j: int) -> list[int]:
    """The rules besides ``j`` that can speak for a document."""
    return [k for k, r in enumerate(rules) if k != j and r.good is not _never]


def _odds(votes: Column, model: Column, rules: tuple[Rule, ...]) -> Column:
    """Per rule, how much likelier its bad vote comes from its kind of junk than from chance; 0 without a bad vote."""

    def odds(j: int) -> Column:
        r = F.get(model, j)
        sound = F.when(_sound(votes, rules, j), r["junk"] / r["good"]).otherwise((1 - r["junk"]) / (1 - r["good"])) if _others(rules, j) else F.lit(1.0)
        return F.when(F.get(votes, j) == -1, (1 - r["false"]) / r["false"] * sound).otherwise(0.0)

    return F.array(*[odds(j) for j in range(len(rules))])


def _sound(votes: Column, rules: tuple[Rule, ...], j: int) -> Column:
    sound = F.lit(True)
    for k in _others(rules, j):
        sound = sound & (F.get(votes, k) == 1)
    return sound


def _posterior(odds: Column) -> Column:
    return 1 / (1 + F.aggregate(odds, F.lit(0.0), lambda t, x: t + x))


def fit_rules(features: DataFrame, rules: tuple[Rule, ...] = RULES, rounds: int = 40) -> list[tuple[float, float, float]]:
    """Per rule: the share of false ones among its bad votes, and how often good documents and its junk are sound elsewhere, by
    expectation-maximisation over the counted vote patterns. Junk is a kind per rule, as kinds hardly overlap; a bad vote on a good document is chance."""
    counted = features.groupBy(_votes(rules).alias("v")).agg(F.count("*").cast("double").alias("n"))
    gathered = counted.agg(F.array_sort(F.collect_list(F.struct("v", "n"))).alias("patterns"))
    total = lambda items, of: F.aggregate(items, F.lit(0.0), lambda t, q: t + of(q))

    def expect(model: Column) -> Column:
        return F.transform("patterns", lambda q: F.struct(q["v"].alias("v"), q["n"].alias("n"), _odds(q["v"], model, rules).alias("odds")))

    def weigh(judged: Column) -> Column:  # documents of a pattern that are good, and that are junk of each rule's kind
        return F.transform(judged, lambda q: F.struct(q["v"].alias("v"), (q["n"] * _posterior(q["odds"])).alias("good"), F.transform(q["odds"], lambda x: x * q["n"] * _posterior(q["odds"])).alias("junk")))

    def maximise(judged: Column) -> Column:
        def rule(j: int) -> Column:
            sound = lambda q, x: F.when(_sound(q["v"], rules, j), x).otherwise(0.0)
            junk = total(judged, lambda q: F.get(q["junk"], j))
            chance = total(judged, lambda q: F.when(F.get(q["v"], j) == -1, q["good"]).otherwise(0.0))
            good = (total(judged, lambda q: sound(q, q["good"])) + 0.9) / (total(judged, lambda q: q["good"]) + 1)
            false = (chance + TRUST * DOUBT / 100) / (chance + junk + TRUST)
            junk_sound = (total(judged, lambda q: sound(q, F.get(q["junk"], j))) + 0.5) / (junk + 1)
            return F.struct(false.alias("false"), good.alias("good"), F.least(junk_sound, APART * good).alias("junk"))

        return F.array(*[rule(j) for j in range(len(rules))])

    # a round is three steps, so that each result is made once: odds of the patterns, documents of each class, model
    empty_odds, empty_judged = F.slice(expect(_start(rules)), 1, 0), F.slice(weigh(expect(_start(rules))), 1, 0)
    start = F.struct(_start(rules).alias("model"), empty_odds.alias("odds"), empty_judged.alias("judged"))

    def step(s: Column, i: Column) -> Column:
        parts = lambda model, odds, judged: F.struct(model.alias("model"), odds.alias("odds"), judged.alias("judged"))
        return (
            F.when(i % 3 == 1, parts(s["model"], expect(s["model"]), s["judged"]))
            .when(i % 3 == 2, parts(s["model"], s["odds"], weigh(s["odds"])))
            .otherwise(parts(maximise(s["judged"]), s["odds"], s["judged"]))
        )

    fitted = gathered.select(F.aggregate(F.sequence(F.lit(1), F.lit(3 * rounds)), start, step)["model"].alias("model")).first()
    return [tuple(r) for r in fitted["model"]]


def _start(rules: tuple[Rule, ...]) -> Column:
    return _constant([(DOUBT, 0.9, 0.5)] * len(rules))


def _constant(model: list[tuple[float, float, float]]) -> Column:
    return F.array(*[F.struct(*[F.lit(x).alias(n) for n, x in zip(("false", "good", "junk"), r)]) for r in model])


def judge(features: DataFrame, model: list[tuple[float, float, float]], rules: tuple[Rule, ...] = RULES, threshold: float = 0.5) -> DataFrame:
    """``features`` with base_failed, quality (posterior) and kept."""
    quality = _posterior(_odds(_votes(rules), _constant(model), rules))
    return features.withColumn("base_failed", base_failed()).withColumn("quality", quality).withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= threshold))


def quality_report(documents: DataFrame) -> DataFrame:
    """One row per document with its counts, posterior and verdict. The features are written once: fitting and judging read them."""
    features = shared.materialize(text_features(documents), "quality-features")
    return judge(features, fit_rules(features))


def keep_good(documents: DataFrame) -> DataFrame:
    """The rows of ``documents`` that are kept, with its columns. Texts are written once beside their features, and aren't shuffled."""
    columns = documents.columns
    packed = documents.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("__row"), F.col("doc_id"), F.col("text"))
    features = shared.materialize(text_features(packed, keep=("__row",)), "quality-rows")
    return judge(features, fit_rules(features)).where("kept").select("__row.*")
