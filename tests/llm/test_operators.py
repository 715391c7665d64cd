"""Each training-data operator against a brute-force version on the smallest tables, and on rows made of edge cases."""

import hashlib
import re
import zlib
from collections import Counter

import compare
import numpy as np
import pytest
from pyspark.sql import functions as F
from topomap.llm import automaton_dedup, catalogue, chunk_codec, embedding_dedup, kd_shards, line_dedup, mixing, near_dedup, quality_rules, shared, suffix_dedup, token_counts, windows
from topomap.llm.components import connected_components
from topomap.llm.shingles import multiset_jaccard, shingle_lists

SF = "/root/testdata/sf0.001"
WORD = re.compile("[^\x20\x09-\x0d]+")
public_tokenizers = pytest.importorskip("public_tokenizers")

PASSAGE = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen"
ODD = [
    (1, None), (2, ""), (3, " \n\t "), (4, PASSAGE + " end."), (5, PASSAGE + " end."), (6, "start " + PASSAGE), (7, "x" * 700), (8, "x" * 300), (9, "naïve café <|endoftext|> 日本語 😀 " * 8),
    (10, "ha " * 400), (11, "a\nb\na\n\n" + PASSAGE), (12, "word"), (13, "word word\r\nword"), (14, (PASSAGE + "\n") * 3), (None, PASSAGE), (15, "́ combining\x1c mark"), (16, PASSAGE.upper() + " é"),
    (4, PASSAGE + " end."), (17, " ".join(f"w{i * i % 99991}" for i in range(150_000))), (2**62 + 1, "a line of its own\n" + PASSAGE + " end."), (-(2**62), "a line of its own"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, blanks, repeats, long runs, a null id, and columns whose names clash with the operators' own."""
    rows = [(i, t, "en" if i else None, "s" if i and i % 2 else None, 0, "k", 1, "x", 7) for i, t in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, id string, size int, words string, node int")


def texts_of(df):
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]


def covered(seqs, width):
    """Per document a mask: covered by a window that starts in a document with a smaller id."""
    first = {}
    for i, s in seqs:
        if i is not None:
            for k in range(len(s) - width + 1):
                w = s[k : k + width]
                first[w] = min(first.get(w, i), i)
    out = []
    for i, s in seqs:
        mark = np.zeros(len(s) + 1, int)
        for k in range(len(s) - width + 1):
            if i is not None and first[s[k : k + width]] < i:
                mark[k] += 1
                mark[k + width] -= 1
        out.append(np.cumsum(mark[:-1]) > 0)
    return out


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_quality_counts(request, which):
    df = request.getfixturevalue(which)
    rows = {r["doc_id"]: r for r in quality_rules.quality_report(df).collect()}
    for i, t in texts_of(df):
        words = WORD.findall(t)
        windows = [tuple(words[k : k + 5]) for k in range(len(words) - 4)]
        counts = Counter(windows)
        repeated = {k + d for k, w in enumerate(windows) if counts[w] > 1 for d in range(5)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        want = (len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(repeated))
        r = rows[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (len(words) < 10 or 100 * len(repeated) > 20 * len(words))
        assert not (r["kept"] and r["base_failed"])


def test_quality_agrees_with_labels(spark):
    sf = "/root/testdata/sf0.01"
    judged = quality_rules.quality_report(spark.read.parquet(f"{sf}/documents.parquet")).join(spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", F.col("quality").alias("label")), "doc_id").where("not base_failed")
    counts = {(r["label"], r["kept"]): r["count"] for r in judged.groupBy("label", "kept").count().collect()}
    good, bad = counts.get((1, True), 0), counts.get((0, False), 0)
    assert good / (good + counts.get((1, False), 0)) > 0.98 and bad / (bad + counts.get((0, True), 0)) > 0.9


def test_a_noisy_rule_is_outweighed(spark):
    """Verse without full stops beside prose: the rule of sentences alone rejects it and is told to be noisy; junk that others don't speak for still goes."""
    word = lambda i, k: "".join(chr(97 + b % 26) for b in hashlib.md5(f"{i} {k}".encode()).digest()[:6])
    prose = lambda i, stop: " ".join(word(i, k) + (stop if k % 10 == 9 else "") for k in range(80))
    verse = [(i, prose(i, "")) for i in range(100)]
    good = [(i, prose(i, ".")) for i in range(100, 300)]
    junk = [(i, " ".join(f"{word(i, k)} $$" for k in range(45)) + " no stop") for i in range(300, 350)]
    report = quality_rules.quality_report(spark.createDataFrame(verse + good + junk, "doc_id long, text string"))
    kept = {r["doc_id"] for r in report.collect() if r["kept"]}
    assert kept >= {i for i, _ in verse + good} and not kept & {i for i, _ in junk}


def test_keep_good_keeps_columns(odd):
    kept = quality_rules.keep_good(odd)
    assert kept.columns == odd.columns and {r["doc_id"] for r in kept.collect()} >= {4, 5, 6}


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_codec_equals_library(request, which):
    from tokenizers import Tokenizer

    df = request.getfixturevalue(which)
    path = public_tokenizers.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    rows = {r["doc_id"]: r for r in chunk_codec.encode_documents(df, path, keep_ids=True).collect()}
    for i, t in texts_of(df):
        ids = lib.encode(t, add_special_tokens=False).ids
        decoded = lib.decode(ids, skip_special_tokens=False)
        r = rows[i]
        assert r["ids"] == ids and r["n_tokens"] == len(ids) and r["decoded"] == decoded
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest() and r["decoded_sha256"] == hashlib.sha256(decoded.encode()).hexdigest()


def test_chunks_are_reused_and_joins_repaired():
    with open(public_tokenizers.path("word_bpe_49k.json"), encoding="utf-8") as f:
        codec = chunk_codec.ChunkCodec(f.read(), bits=6, least=32)
    body = " ".join(f"word{i} runs{i * 7}" for i in range(400))
    alone = codec.encode([body])[0]
    assert codec.encode(["other start " + body])[0][0].endswith(alone[0][-200:]) and codec.reused_chunks > 50 and codec.whole_texts == 0
    for text in (body, "other start " + body, "é́ " * 90, "x" * 500, "ab'sc " * 100):
        ids = codec.tokenizer.encode(text, add_special_tokens=False).ids
        assert codec.encode([text])[0][0] == " ".join(map(str, ids))


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_token_counts_equal_library(request, which):
    from tokenizers import Tokenizer

    df = request.getfixturevalue(which)
    path = public_tokenizers.path("byte_bpe_50k.json")
    lib = Tokenizer.from_file(path)
    rows = {r["doc_id"]: r for r in token_counts.count_tokens(df, path, 512).collect()}
    for i, t in texts_of(df):
        n = len(lib.encode(t, add_special_tokens=False).ids)
        assert (rows[i]["n_bytes"], rows[i]["n_tokens"], rows[i]["over_limit"]) == (len(t.encode()), n, n > 512)


def test_vectors_against_all_pairs(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(40, 64))
    x = np.concatenate([base, base + 0.04 * rng.normal(size=base.shape) * np.linalg.norm(base, axis=1, keepdims=True) / 8 * 8, base[:5], 3 * base[5:8]])
    rows = [(i, [float(v) for v in r], int(i % 2 if i < 80 else (i - 80) % 2)) for i, r in enumerate(x)]
    rows += [(500, None, 1), (501, [0.0] * 64, 1), (502, [None] * 64, 1), (503, [float("nan")] * 64, 1), (504, rows[0][1], None), (505, [], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = {r["vec_id"]: r for r in embedding_dedup.linked_vectors(df).collect()}
    ids = list(range(len(x)))
    cos = (x @ x.T) / np.outer(np.linalg.norm(x, axis=1), np.linalg.norm(x, axis=1))
    label = np.array([r[2] for r in rows[: len(x)]])
    link = (cos >= 0.93) & (label[:, None] == label[None]) & ~np.eye(len(x), dtype=bool)
    component = np.array(ids)
    for _ in ids:
        component = np.array([min([component[i], *component[link[i]]]) for i in ids])
    for i in ids:
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (link[i].sum(), component[i], component[i] == i)
    for i in range(500, 506):
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (0, i, True)
    assert link.sum() > 20


@pytest.mark.parametrize("dim", [1, 2, 3, 4])
def test_short_vectors_against_all_pairs(spark, dim):
    rng = np.random.default_rng(dim)
    x = rng.normal(size=(300, dim))
    df = spark.createDataFrame([(i, [float(v) for v in r], 0) for i, r in enumerate(x)], "vec_id long, embedding array<double>, label int")
    got = {r["vec_id"]: r["n_links"] for r in embedding_dedup.linked_vectors(df).collect()}
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    link = (unit @ unit.T >= 0.93) & ~np.eye(len(x), dtype=bool)
    assert [got[i] for i in range(len(x))] == link.sum(axis=1).tolist()


def test_signatures_estimate_weighted_jaccard():
    rng = np.random.default_rng(5)
    a = np.sort(rng.integers(0, 2**63, 900).astype(np.uint64))
    b = np.sort(np.concatenate([a[:700], np.repeat(a[:50], 5), rng.integers(0, 2**63, 100).astype(np.uint64)]))
    s = near_dedup.bag_signatures([a, b], 4000)
    assert abs((s[0] == s[1]).mean() - multiset_jaccard(a, b)) < 0.03


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_near_duplicates_against_all_pairs(request, which):
    df = request.getfixturevalue(which)
    got = {r["id"]: r["component"] for r in near_dedup.near_duplicates(df).collect()}
    listed = [(i, t) for i, t in texts_of(df) if i is not None]
    bags = {i: b for (i, _), b in zip(listed, shingle_lists([t for _, t in listed], 5)) if len(b)}
    ids = sorted(bags)
    component = {i: i for i in ids}
    links = [(a, b) for a in ids for b in ids if a < b and min(len(bags[a]), len(bags[b])) >= 0.8 * max(len(bags[a]), len(bags[b])) and multiset_jaccard(bags[a], bags[b]) >= 0.8]
    for _ in ids:
        for a, b in links:
            component[a] = component[b] = min(component[a], component[b])
    assert got == component
    kept = near_dedup.keep_one_each(df)
    assert kept.columns == df.columns and {r["doc_id"] for r in kept.collect() if r["doc_id"] in component} == set(component.values())


def test_components_of_a_chain_and_a_star(spark):
    edges = [(i, i + 1) for i in range(100, 140)] + [(7, i) for i in range(200, 240)] + [(5, 5), (1, 2), (2, 1)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert {got[i] for i in range(100, 141)} == {100} and {got[i] for i in range(200, 240)} == {7} == {got[7]} and got[2] == got[1] == 1
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_shards(request, which):
    df = request.getfixturevalue(which)
    rows = kd_shards.shard_documents(df, shards=16).collect()
    assert len(rows) == df.count() and {r["shard"] for r in rows} <= set(range(16))
    text = dict(texts_of(df))
    for r in rows:
        raw = text[r["doc_id"]].encode()
        assert r["size"] == len(raw) + 1 and r["text_crc32"] in (zlib.crc32(raw), None)
    for s in {r["shard"] for r in rows}:
        assert sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(sum(r["shard"] == s for r in rows)))
    if which == "docs":
        sizes = [sum(r["size"] for r in rows if r["shard"] == s) for s in range(16)]
        assert max(sizes) - min(sizes) <= 0.2 * np.mean(sizes) + max(r["size"] for r in rows)
        assert len({r["shard"] for r in kd_shards.shard_documents(df, target_bytes=sum(sizes) // 5).collect()}) >= 5


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_suffix_dedup_against_all_windows(request, which):
    df = request.getfixturevalue(which)
    got = {r["doc_id"]: r for r in suffix_dedup.remove_repeated_bytes(df.repartition(3), keep_bytes=True).collect()}
    seqs = [(i, t.encode()) for i, t in texts_of(df)]
    for (i, raw), gone in zip(seqs, covered(seqs, 50)):
        kept = np.frombuffer(raw, np.uint8)[~gone].tobytes()
        r = got[i]
        assert (r["n_bytes"], r["n_removed"], r["n_spans"]) == (len(raw), gone.sum(), (np.diff(gone.astype(int), prepend=0) == 1).sum())
        assert bytes(r["kept"]) == kept and r["kept_sha256"] == hashlib.sha256(kept).hexdigest()


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_automaton_dedup_against_all_windows(request, which):
    df = request.getfixturevalue(which)
    got = {r["doc_id"]: r for r in automaton_dedup.remove_repeated_words(df.repartition(3), keep_text=True).collect()}
    seqs = [(i, tuple(WORD.findall(t))) for i, t in texts_of(df)]
    for (i, words), gone in zip(seqs, covered(seqs, 13)):
        kept = " ".join(w for w, g in zip(words, gone) if not g)
        assert (got[i]["n_words"], got[i]["n_removed"], got[i]["kept"], got[i]["kept_sha256"]) == (len(words), gone.sum(), kept, hashlib.sha256(kept.encode()).hexdigest())


def test_hot_passages_are_settled_across_tasks(spark, monkeypatch):
    """A passage of very many documents: its contexts are settled once more, with the same result."""
    monkeypatch.setattr(windows, "REPORTED", 2)
    monkeypatch.setattr(windows, "HOT_ROWS", 10)
    common = prose(5, 40)
    rows = [(i, (prose(100 + i % 9, 12) + " " if i % 3 else "") + common + (" " + prose(200 + i % 7, 12) if i % 5 else "")) for i in range(90)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(12)
    got = {r["doc_id"]: r["n_removed"] for r in suffix_dedup.remove_repeated_bytes(df).collect()}
    assert got == {i: int(gone.sum()) for (i, _), gone in zip(rows, covered([(i, t.encode()) for i, t in rows], 50))}
    got = {r["doc_id"]: r["n_removed"] for r in automaton_dedup.remove_repeated_words(df).collect()}
    assert got == {i: int(gone.sum()) for (i, _), gone in zip(rows, covered([(i, tuple(WORD.findall(t))) for i, t in rows], 13))}


def test_suffix_automaton_finds_the_smallest_document():
    rng = np.random.default_rng(1)
    seqs = [(d, rng.integers(0, 3, 30).tolist()) for d in (5, 2, 9, 4)]
    a = automaton_dedup.SuffixAutomaton()
    for d, s in seqs:
        a.add(s, d)
    a.finish()
    for _, s in seqs:
        want = [min(d for d, o in seqs if any(o[j : j + 4] == s[k : k + 4] for j in range(27))) for k in range(27)]
        assert a.earliest(s, 4) == want


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_mixing(request, which):
    df = request.getfixturevalue(which)
    size = shared.word_count(F.col("text"))
    plan = mixing.mixing_plan(df, size=size).collect()
    assert len(plan) == df.count() and all(r["copies"] <= 3 for r in plan)
    total = sum(r["size"] for r in plan)
    targets = {r["source"]: (r["source_size"], r["target"]) for r in plan}
    # resharing until none is above three times its size
    order = sorted(targets, key=lambda s: (s is None, s or ""))
    weight = {s: (1, 2, 3)[k % 3] for k, s in enumerate(order)}
    want, open_, left = {}, set(order), float(total)
    while open_:
        share = {s: left * weight[s] / sum(weight[o] for o in open_) for s in open_}
        full = {s for s in open_ if share[s] >= 3 * targets[s][0]}
        if not full:
            want |= share
            break
        for s in full:
            want[s] = 3.0 * targets[s][0]
            left -= want[s]
        open_ -= full
    assert {s: pytest.approx(v) for s, v in want.items()} == {s: t for s, (_, t) in targets.items()}
    mixed = mixing.mix(df, size=size)
    assert mixed.columns == df.columns
    counts = Counter((r["doc_id"], r["text"]) for r in mixed.collect())
    assert sum(counts.values()) == sum(r["copies"] for r in plan)


def lines_removed(listed, num=4, den=5):
    earlier, gone = [], set()
    for i, t in listed:
        for k, line in enumerate(t.split("\n")):
            s = frozenset(WORD.findall(line))
            if s:
                if any(den * len(s & o) >= num * len(s | o) for o in earlier):
                    gone.add((i, k))
                earlier.append(s)
    return gone


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_line_dedup_against_all_pairs(request, which):
    df = request.getfixturevalue(which)
    rows = {r["doc_id"]: r for r in line_dedup.line_report(df).collect()}
    listed = sorted({(i, t) for i, t in texts_of(df) if i is not None})
    gone = lines_removed(listed)
    for i, t in listed:
        kept = "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone)
        assert (rows[i]["n_removed"], rows[i]["kept_sha256"]) == (sum(a == i for a, _ in gone), hashlib.sha256(kept.encode()).hexdigest())
    left = line_dedup.drop_repeated_lines(df)
    assert left.columns == df.columns and 5 not in {r["doc_id"] for r in left.collect()} or which == "docs"


def test_line_dedup_tries_every_hub(spark):
    """A copy whose few edits stand in an earlier, unlike line: no word has more than two lines, and the first trial is a false one."""
    for seed in range(3):
        w = [f"s{seed}w{k}" for k in range(8000)]
        unlike, like = w[:4000], w[4000:8000]
        listed = [(1, " ".join(unlike)), (2, " ".join(like)), (3, " ".join(like[200:] + unlike[:200]))]
        rows = line_dedup.line_report(spark.createDataFrame(listed, "doc_id long, text string")).collect()
        assert {(r["doc_id"], 0) for r in rows if r["n_removed"]} == lines_removed(listed) == {(3, 0)}


def test_line_dedup_bits_tell_half_equal_lines_apart(spark):
    """Lines of 48 words that share 30 are no candidates to be verified: at most one pair in fifty passes the bits."""
    rows = [(k, *[[(k << 20) + 7919 * w * w + w for w in ws] for ws in (range(48), [*range(30), *range(100, 118)])]) for k in range(200)]
    x, y = (F.transform(c, lambda t: F.xxhash64(t)) for c in "xy")
    n = F.lit(48)
    passed = spark.createDataFrame(rows, "k long, x array<long>, y array<long>").where(line_dedup._may_match(n, F.lit(0), line_dedup._bitmap(x), n, F.lit(0), line_dedup._bitmap(y))).count()
    assert passed <= 4


def test_line_dedup_bits_tell_long_lines_apart(spark):
    """Lines of 200 words that share 100 may differ in 44 places of the bits by their length, and differ in more; alike ones pass; the lanes of a long line fold to the bits of a short one."""
    rows = [(k, *[[(k << 20) + 7919 * w * w + w for w in ws] for ws in (range(200), [*range(100), *range(300, 400)], [*range(190), *range(300, 310)], range(64))]) for k in range(200)]
    x, y, z, s = (F.transform(c, lambda t: F.xxhash64(t)) for c in "xyzs")
    n = F.lit(200)
    df = spark.createDataFrame(rows, "k long, x array<long>, y array<long>, z array<long>, s array<long>")
    bits = df.select(*[line_dedup._bitmap(c).alias(k) for k, c in zip("xyzs", (x, y, z, s))], line_dedup._parities(x).alias("px"), line_dedup._parities(s).alias("ps")).collect()
    passed = df.where(line_dedup._may_match(n, F.lit(0), line_dedup._bitmap(x), n, F.lit(0), line_dedup._bitmap(y))).count()
    alike = df.where(line_dedup._may_match(n, F.lit(0), line_dedup._bitmap(x), n, F.lit(0), line_dedup._bitmap(z))).count()
    assert passed <= 4 and alike == 200
    assert all(r["x"][0] ^ r["x"][1] ^ r["x"][2] ^ r["x"][3] == r["px"] and r["s"] == [r["ps"], 0, 0, 0] for r in bits)


def test_line_dedup_filter_of_documents_loses_none(spark):
    ids = spark.range(0, 40_000, 4).withColumn("id", F.col("id") - 20_000)
    known = line_dedup._may_be_in(ids)
    passed = {r["id"] for r in spark.range(-20_000, 20_000).where(known(F.col("id"))).collect()}
    assert set(range(-20_000, 20_000, 4)) <= passed and len(passed) < 11_000


def test_line_dedup_moves_only_lines_it_verifies(spark, monkeypatch):
    """Documents whose lines are verified move once, whole; their lines are not shuffled."""
    plans, real = [], shared.materialize
    monkeypatch.setattr(shared, "materialize", lambda df, label: (label == "line-tokens" and plans.append(df._jdf.queryExecution().executedPlan().toString()), real(df, label))[1])
    listed = [(1, "a b c d e f g h i j\nk l m n o"), (2, "a b c d e f g h i j k\np q r s t")]
    limit = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "-1")
    try:
        rows = {r["doc_id"]: r["n_removed"] for r in line_dedup.line_report(spark.createDataFrame(listed, "doc_id long, text string")).collect()}
    finally:
        spark.conf.set(limit, before)
    assert rows == {1: 0, 2: 1} and plans and all(p.index("Generate") < p.index("Exchange") for p in plans)


def test_line_dedup_of_wide_ids(spark):
    texts = ["a b\nc d\ne f", "c d\nx y\ng h", "x y\nz z z\na b", "k l\nm n\ng h"]
    listed = list(zip([-(2**63), -(2**62) - 5, 2**62, 2**63 - 1], texts))
    rows = {r["doc_id"]: r for r in line_dedup.line_report(spark.createDataFrame(listed, "doc_id long, text string")).collect()}
    gone = lines_removed(listed)
    for i, t in listed:
        kept = "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone)
        assert (rows[i]["n_removed"], rows[i]["kept_sha256"]) == (sum(a == i for a, _ in gone), hashlib.sha256(kept.encode()).hexdigest())


def prose(seed, n=60):
    rng = np.random.default_rng(seed)
    return " ".join("".join(chr(97 + c) for c in rng.integers(0, 26, 6)) for _ in range(n))


def clash(spark):
    """A document 2 of two texts, one a copy of document 1, the other its own, and rows that repeat one whole."""
    rows = [(1, prose(1)), (2, prose(1)), (2, prose(2)), (2, prose(2)), (3, prose(2) + "\n" + prose(3)), (3, prose(2) + "\n" + prose(3))]
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_texts_of_one_id_keep_what_is_theirs(spark):
    df = clash(spark)
    removed = {(r["doc_id"], r["n_bytes"], r["n_removed"]) for r in suffix_dedup.remove_repeated_bytes(df).collect()}
    assert removed == {(1, len(prose(1)), 0), (2, len(prose(1)), len(prose(1))), (2, len(prose(2)), 0), (3, len(prose(2)) + 1 + len(prose(3)), len(prose(2)))}
    words = {(r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in automaton_dedup.remove_repeated_words(df).collect()}
    sha = lambda t: hashlib.sha256(t.encode()).hexdigest()
    assert words == {(1, 60, 0, sha(prose(1))), (2, 60, 60, sha("")), (2, 60, 0, sha(prose(2))), (3, 120, 60, sha(prose(3)))}
    lines = {(r["doc_id"], r["n_removed"], r["kept_sha256"]) for r in line_dedup.line_report(df).collect()}
    assert lines == {(1, 0, sha(prose(1))), (2, 1, sha("")), (2, 0, sha(prose(2))), (3, 1, sha(prose(3)))}
    # a document takes part with each of its texts
    longer = spark.createDataFrame([(4, prose(2)), (5, prose(9))], "doc_id long, text string")
    assert {(r["id"], r["component"]) for r in near_dedup.near_duplicates(df.union(longer)).collect()} == {(1, 1), (2, 1), (3, 3), (4, 1), (5, 5)}


def test_signatures_are_functions_of_the_bag(docs):
    """Alone or inside any batch, in any number of partitions."""
    rng = np.random.default_rng(0)
    bags = [np.sort(np.concatenate([b, b[: len(b) // 3], b[: len(b) // 9]])) for b in (rng.integers(0, 2**63, n).astype(np.uint64) for n in (1, 2, 50, 700, 4000, 9, 30, 120))]
    together = near_dedup.bag_signatures(bags * 40, 160)
    assert all((together[i + 8 * j] == near_dedup.bag_signatures([b], 160)[0]).all() for i, b in enumerate(bags) for j in (0, 39))
    keys = lambda n: {r["id"]: r["bands"] for r in near_dedup.signature_table(docs.repartition(n)).select("id", "bands").collect()}
    assert keys(1) == keys(60)


def test_near_duplicates_at_the_threshold_are_found(spark):
    """Pairs whose shingles overlap by 0.8 to 0.84, and a group around one text whose outer members only meet through others."""
    rng = np.random.default_rng(4)
    rows = []
    for k in range(150):
        words = prose(1000 + k, 200).split()
        rows.append((2 * k, " ".join(words)))
        for _ in range(50):
            other = list(words)
            for at in rng.choice(200, 4, replace=False):
                other[at] = "changed" + str(at)
            a, b = shingle_lists([rows[-1][1], " ".join(other)], 5)
            if 0.8 <= multiset_jaccard(a, b) <= 0.84:
                break
        rows.append((2 * k + 1, " ".join(other)))
    base = prose(77, 150).split()
    for k in range(200):
        edited = list(base)
        for at in rng.choice(150, int(rng.integers(0, 6)), replace=False):
            edited[at] = f"edit{rng.integers(0, 40)}"
        rows.append((10_000 + k, " ".join(edited)))
    got = {r["id"]: r["component"] for r in near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    bags = dict(zip([i for i, _ in rows], shingle_lists([t for _, t in rows], 5)))
    wanted = [k for k in range(150) if multiset_jaccard(bags[2 * k], bags[2 * k + 1]) >= 0.8]
    assert len(wanted) > 100 and sum(got[2 * k + 1] == 2 * k for k in wanted) >= 0.99 * len(wanted)
    group = [i for i in bags if i >= 10_000]
    component = {i: i for i in group}
    links = [(a, b) for a in group for b in group if a < b and multiset_jaccard(bags[a], bags[b]) >= 0.8]
    for _ in group:
        for a, b in links:
            component[a] = component[b] = min(component[a], component[b])
    assert {i: got[i] for i in group} == component and len(set(component.values())) > 2


def test_links_of_large_labels_are_found(spark):
    """Labels of thousands of vectors, for which there are several tables: every planted pair above the threshold is linked."""
    rng = np.random.default_rng(8)
    x = rng.normal(size=(6000, 32))
    x[3000:] = x[:3000] + 0.36 * rng.normal(size=(3000, 32)) * np.linalg.norm(x[:3000], axis=1, keepdims=True) / 32**0.5
    df = spark.createDataFrame([(i, [float(v) for v in r], 1) for i, r in enumerate(x)], "vec_id long, embedding array<double>, label int")
    got = {r["vec_id"]: r["n_links"] for r in embedding_dedup.linked_vectors(df).collect()}
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = (unit @ unit.T >= 0.93).sum(axis=1) - 1
    assert want.sum() > 1500 and sum(got[i] for i in range(6000)) >= 0.999 * want.sum() and all(got[i] <= want[i] for i in range(6000))


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()))
def test_twin(spark, name):
    assert compare.mismatch(spark, SF, catalogue.queries()[name], catalogue.oracle_sql()[name]) == ""


@pytest.mark.parametrize("name", list(catalogue.queries()))
def test_empty_tables(spark, tmp_path, name):
    for t in ("documents", "embeddings"):
        spark.read.parquet(f"{SF}/{t}.parquet").limit(0).write.parquet(str(tmp_path / f"{t}.parquet"))
    assert catalogue.queries()[name](spark, str(tmp_path)).count() == 0


def near_components(listed):
    bags = {i: b for (i, _), b in zip(listed, shingle_lists([t for _, t in listed], 5)) if len(b)}
    component = {i: i for i in bags}
    links = [(a, b) for a in bags for b in bags if a < b and min(len(bags[a]), len(bags[b])) >= 0.8 * max(len(bags[a]), len(bags[b])) and multiset_jaccard(bags[a], bags[b]) >= 0.8]
    for _ in bags:
        for a, b in links:
            component[a] = component[b] = min(component[a], component[b])
    return component


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_pipeline_stages(spark, request, which):
    """Each stage on what the one before kept, against a brute-force version of its own."""
    import corpus_pipeline
    from tokenizers import Tokenizer

    df = request.getfixturevalue(which)
    columns, step = df.columns, df
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = Counter(texts_of(step))
        listed = sorted({x for x in before if x[0] is not None})
        kept = {(r["doc_id"], r["n_words"]): r["kept"] for r in quality_rules.quality_report(step).collect()} if name == "quality" else {}
        copies = Counter({(r["doc_id"], r["size"]): r["copies"] for r in mixing.mixing_plan(step, size=shared.word_count(F.col("text"))).collect()}) if name == "weights" else {}
        step = shared.materialize(stage(spark, step, SF), f"test-{name}")
        assert step.columns == columns and step.count() > 0
        after = Counter(texts_of(step))
        if name == "quality":
            assert after == Counter({x: n for x, n in before.items() if kept[x[0], len(WORD.findall(x[1]))]})
        elif name == "lines":
            gone = lines_removed(listed)
            left = [(i, "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone) if any(i == g for g, _ in gone) else t) for i, t in listed]
            assert {x for x in after if x[0] is not None} == {x for x in left if x[1] in dict(listed).values() or WORD.search(x[1])}
        elif name == "near_copies":
            component = near_components(listed)
            assert {i for i, _ in after if i is not None} == {i for i, _ in listed if component.get(i, i) == i}
        else:
            assert after == Counter({x: n * copies[x[0], len(WORD.findall(x[1]))] for x, n in before.items() if copies[x[0], len(WORD.findall(x[1]))]})
    last = corpus_pipeline.STAGES[-1][1](spark, step, SF)
    lib = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    text = dict(texts_of(step))
    assert last.count() == step.count()
    for r in last.collect():
        assert r["n_tokens"] == len(lib.encode(text[r["doc_id"]], add_special_tokens=False).ids)
