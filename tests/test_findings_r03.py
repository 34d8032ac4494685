"""The third round's findings: how memory, disk and time grow, and that results stay whole."""

from __future__ import annotations

import random
import time
import tracemalloc

import numpy as np

from textfactor.kernels import batch, edit, index
from textfactor.llm import lm_score


def peak_of(call):
    tracemalloc.start()
    try:
        return call(), tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()


def test_f1_workers_map_one_file(spark, monkeypatch):
    """Filter and exact counts lie in a file; neither the workers' task nor a broadcast carries them."""
    rows = [(k, " ".join(f"w{(k * j) % 977}" for j in range(60))) for k in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    scratch = lm_score.Scratch(spark, "lm-test")
    table = scratch.write(lm_score.count_and_build(docs, 16, 10, 7), "shards")
    places, where = lm_score.write_held(scratch, table, 16)
    words = lm_score.mapped(where())
    assert isinstance(words.base, np.memmap) and words.base.mode == "r"
    count = {}
    for _, text in rows:
        for w in text.split():
            count[w] = count.get(w, 0) + 1
    names = [*count, "unseen"]
    keys, _ = lm_score.word_keys([w.encode() for w in names])
    levels, exact = places.over(words, 7).words(keys)
    assert exact.tolist() == [count.get(w, 0) for w in names]
    assert (levels >= lm_score.level_of(exact)).all() and lm_score.mapped(where()) is words
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda *a: (_ for _ in ()).throw(AssertionError("broadcast")))
    assert lm_score.score(docs, lm_score.F.lit(True)).count() == len(rows)


def test_f1_no_training_rows(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, None)], "doc_id long, text string")
    for bound in (0, 1 << 20):
        got = lm_score.score(docs, lm_score.F.lit(False), max_broadcast_bytes=bound).collect()
        assert sorted((r.doc_id, r.n_tokens, r.n_known) for r in got) == [(1, 3, 0), (2, 1, 0)]


def test_f1_probing_holds_pieces():
    """What the probes of many keys hold at a time does not grow with their number."""
    rng = np.random.default_rng(3)
    size = 64 * 4000
    found = lm_score.LogFrequencyFilter([(0, size, bytes([255]) * 2 + bytes(size // 8 - 2))], 1, 7)
    keys = rng.integers(0, 2**63, 2_000_000).astype(np.uint64)
    levels, peak = peak_of(lambda: found.levels(keys))
    assert len(levels) == len(keys) and peak < 96 << 20


def test_f6_many_pairs_at_a_time():
    rng = random.Random(6)
    word = lambda n, letters: "".join(rng.choice(letters) for _ in range(rng.randrange(n + 1)))
    for letters in ("ab", "vcsep", "aé\U0001f600\0 ", [chr(k) for k in range(100, 2000)]):
        for n in (3, 70, 140, 300):
            a, b = [word(n, letters) for _ in range(60)], [word(n, letters) for _ in range(60)]
            b[:20] = [t[: len(t) // 2] + "x" + t[len(t) // 2 :] for t in a[:20]]
            want = [edit.ed_dp(x, y) for x, y in zip(a, b, strict=True)]
            assert batch.ed_dp(a, b).tolist() == want == batch.ed_diagonal_auto(a, b).tolist()
    assert batch.ed_dp([], []).tolist() == [] == batch.ed_diagonal_auto([], []).tolist()
    a, b = [word(99, "vcsep") for _ in range(3000)], [word(99, "vcsep") for _ in range(3000)]
    begun = time.process_time()
    batch.ed_dp(a, b), batch.ed_diagonal_auto(a, b)
    many, begun = time.process_time() - begun, time.process_time()
    for x, y in zip(a[:300], b, strict=False):
        edit.ed_dp(x, y), edit.ed_diagonal_auto(x, y)
    assert many < (time.process_time() - begun) * 10 / 4


def test_f6_rows_of_both_methods(spark):
    from textfactor.operators import rows

    given = [(1, "abc", "abc"), (2, "abc", "xbcd"), (3, "", "ab"), (4, None, "a"), (5, "a", None), (6, "a" * 300, "b" + "a" * 290)]
    df = spark.createDataFrame(given, "i long, a string, b string")
    got = {r.i: r for r in rows.edit_distances(df, "a", "b", ["i"], [("dp", None), ("diagonal_auto", None)]).collect()}
    assert {i: (r.distance, r.distance_2) for i, r in got.items()} == {i: (d := edit.ed_dp(x, y), d) for i, x, y in given if x is not None and y is not None}
    other = rows.edit_distances(df, "a", "b", ["i"], [("dp", None), ("diagonal_auto", None), ("ideal", None)])
    assert other.drop("distance_3").schema == rows.edit_distances(df, "a", "b", ["i"], [("dp", None), ("diagonal_auto", None)]).schema
    assert all(r.oracle_reads == 0 and r.q_tokens == 0 for r in got.values())
    assert {r.i: r.distance for r in rows.edit_distance(df, "a", "b", ["i"], "dp", 2).collect()} == {1: 0, 2: 2, 3: 2, 6: -1}


def test_f5_all_patterns_at_once():
    rng = random.Random(5)
    word = lambda n, letters: "".join(rng.choice(letters) for _ in range(n))
    for letters in ("a", "ab", "aé\U0001f600 "):
        patterns = sorted({word(rng.randrange(1, 7), letters) for _ in range(60)} | {"zz", "", "a" * 40})
        ready = index.Patterns(patterns)
        for n in (0, 1, 17, 200):
            text = word(n, letters)
            found = index.FmIndex(text)
            count, at = found.locate_all(ready)
            want = [found.locate(p) for p in patterns]
            assert count.tolist() == [len(w) for w in want] and at.tolist() == [v for w in want for v in w]
            assert all(w == [k for k in range(n) if text.startswith(p, k)] for p, w in zip(patterns, want, strict=True) if p)
    assert [len(x) for x in index.FmIndex("ab").locate_all(index.Patterns([]))] == [0, 0]


def test_f5_time_of_many_patterns():
    rng = random.Random(5)
    text = "".join(rng.choice("abcdefgh ") for _ in range(600))
    patterns = sorted({"".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 9))) for _ in range(1500)})
    ready, found = index.Patterns(patterns), index.FmIndex(text)
    found.locate("a")
    begun = time.process_time()
    for _ in range(5):
        found.locate_all(ready)
    many, begun = (time.process_time() - begun) / 5, time.process_time()
    for p in patterns:
        found.locate(p)
    assert many < (time.process_time() - begun) / 2


def test_f5_lists_and_columns_of_patterns(spark):
    from textfactor.operators import rows

    texts = spark.createDataFrame([(1, "abracadabra"), (2, ""), (3, None), (4, "bab")], "i long, t string")
    words = ["a", "ab", "bra", "x"]
    wanted = sorted((i, p, len(at), v) for i, t in ((1, "abracadabra"), (4, "bab")) for p in words for at in [[k for k in range(len(t)) if t.startswith(p, k)]] for v in at)
    for kind in ("run", "fm"):
        assert sorted(map(tuple, rows.pattern_occurrences(texts, "t", words, ["i"], kind).collect())) == wanted
    column = rows.pattern_occurrences(texts.withColumn("w", lm_score.F.array(*map(lm_score.F.lit, words))), "t", "w", ["i"], "fm")
    assert sorted(map(tuple, column.where("pos is not null").collect())) == wanted
