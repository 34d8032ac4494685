"""Small cases of the second round's findings."""

import random

from compare import same_rows

from textfactor import catalog as queries
from textfactor.kernels import edit


def _write(spark, path, name, rows, ddl):
    spark.createDataFrame(rows, ddl).repartition(2).write.parquet(f"{path}/{name}.parquet")


def test_one_edit_join_by_brute_force(spark):
    from textfactor.operators import joins

    rng = random.Random(7)
    texts = ["", "a", "b", "aa", "ab", "ba", "é", "éa"] + ["".join(rng.choice("abé") for _ in range(rng.randrange(6))) for _ in range(60)]
    left, right = list(enumerate(texts[::2])), list(enumerate(texts[1::2]))
    a, b = spark.createDataFrame([*left, (-1, None)], "i long, t string"), spark.createDataFrame([*right, (-1, None)], "i long, t string")
    found = sorted(map(tuple, joins.similarity_join(a, b, "i", "i", "t", "t", 1).collect()))
    assert found == sorted((i, j, d) for i, x in left for j, y in right if (d := edit.ed_dp(x, y)) <= 1)
    own = sorted(map(tuple, joins.similarity_join(a, a, "i", "i", "t", "t", 1, self_join=True).collect()))
    assert own == sorted((i, j, d) for i, x in left for j, y in left if i < j and (d := edit.ed_dp(x, y)) <= 1)


def test_copies_are_not_expanded_into_pairs(spark, duck, tmp_path):
    names = ["Supplier#01", "Supplier#02", "Supplier#12", None, "X"]
    _write(spark, tmp_path, "supplier", [(k, names[k % 5]) for k in range(100)], "s_suppkey long, s_name string")
    _write(spark, tmp_path, "customer", [(k, names[k % 5]) for k in range(100)], "c_custkey long, c_name string")
    for table, query in (("supplier", "similarity_join_suppliers"), ("customer", "similarity_join_customers")):
        got = queries.QUERIES[query](spark, str(tmp_path))
        assert got.count() == 4 * 19 + 2
        sql = queries.ORACLES[query].replace(f"from {table}", f"from '{tmp_path}/{table}.parquet/*.parquet'")
        assert same_rows(got.toPandas(), duck.sql(sql).df()) == ""


def test_set_operations_never_broadcast_occurrences(spark, sf):
    from textfactor.plans.rewrite import plan_text

    assert "BroadcastExchange" not in plan_text(queries.QUERIES["qgram_set_operations"](spark, sf))


def _near(rng, symbols):
    x = [rng.choice(symbols) for _ in range(rng.randrange(24))]
    y = x[:]
    for _ in range(rng.randrange(6)):
        p = rng.randrange(len(y) + 1)
        y[p : p + rng.randrange(2)] = rng.choices(symbols, k=rng.randrange(2))
    return "".join(x), "".join(y)


def _plain(x, y):
    row = list(range(len(y) + 1))
    for i, a in enumerate(x):
        new = [i + 1]
        for j, b in enumerate(y):
            new.append(min(new[-1] + 1, row[j + 1] + 1, row[j] + (a != b)))
        row = new
    return row


def test_distances_by_brute_force():
    rng = random.Random(11)
    for _ in range(400):
        x, y = _near(rng, rng.choice(["ab", "abcdé~"]))
        row = _plain(x, y)
        assert edit.ed_prefixes(x, y) == row and edit.ed_dp(x, y) == row[-1] == edit.ed_diagonal_auto(x, y)
        for k in (0, 1, 2, 4, 30):
            found = edit.ed_diagonal(x, y, k, script=True)
            assert edit.ed_diagonal(x, y, k) == (row[-1] if row[-1] <= k else None) == (found and found[0])
            assert found is None or (len(found[1]) == row[-1] and edit.apply_edits(x, found[1]) == [ord(c) for c in y])


def test_many_ones_without_a_wave_each(monkeypatch):
    monkeypatch.setattr(edit.DirectExtensions, "lce", None)  # a wave for each one would call it
    bits = "0010" * 50_000
    assert edit.ed_diagonal_auto(bits, "0" * len(bits)) == 50_000
    assert edit.ed_diagonal([0, 1, 2], [0, 2, 2], 1, script=True) == (1, [("S", 1, 1, 2)])


def test_windows_of_few_phrases_are_not_factorized(monkeypatch):
    from textfactor.kernels import anchor

    rng = random.Random(5)
    for _ in range(100):
        x, y = _near(rng, "abc")
        for pos in range(len(x) + 1):
            for k in (0, 1, 2):
                assert anchor.window_bounds(x, pos, k, 1, 1) == anchor.context_window(x, pos, k, 1, 1)[:2]
            k = edit.ed_dp(x, y)
            assert anchor.test_all_anchors(x, y, k, pos) == [anchor.test_anchor(x, y, k, pos, at) for at in range(len(y) + 1)]
    monkeypatch.setattr(anchor, "prefix_phrases", None)
    words = " ".join(rng.choice(["one", "two", "three"]) for _ in range(5000))
    assert anchor.window_bounds(words, len(words) // 2, 800) == (0, len(words))


def test_a_restarted_part_is_run_once(monkeypatch):
    from textfactor.kernels import solve

    calls, find = [], solve.find_anchor
    monkeypatch.setattr(solve, "find_anchor", lambda *a: calls.append(a) or find(*a))
    rng = random.Random(3)
    x, y = ("".join(rng.choice("vcsep") for _ in range(40)) for _ in range(2))
    distance, ledger = solve.solve_restart(x, y)
    assert distance == _plain(x, y)[-1] and ledger.restarts > len(set(calls)) == len(calls)


def test_distances_in_one_pass(spark):
    from textfactor.operators import rows

    texts = [(0, "abc", "abc"), (1, "abc", "xbc"), (2, None, "a"), (3, "", "ab"), (4, "abcd", "d")]
    df = spark.createDataFrame(texts, "id int, a string, b string")
    got = {r.id: (r.distance, r.distance_2, r.q_tokens > 0) for r in rows.edit_distances(df, "a", "b", ["id"], [("anchor", None), ("diagonal", 1)]).collect()}
    assert got == {0: (0, 0, False), 1: (1, 1, True), 3: (2, -1, False), 4: (3, -1, True)}
    assert {r.id: r.distance for r in rows.edit_distance(df, "a", "b", ["id"], "dp", 2).collect()} == {0: 0, 1: 1, 3: 2, 4: -1}


def test_overlap_takes_only_items_that_share_a_gram(spark, tmp_path, monkeypatch):
    from textfactor.kernels import apps

    rng = random.Random(2)
    items = ["".join(rng.choice("abcdef gh") for _ in range(90)) for _ in range(5)] + [None]
    texts = [items[0][7:31] + "x" * 40, "y" * 13 + items[1][3:26] + "z" * 30, "q" + items[2] + items[3][:50], "", None, "short", items[4][-30:]]
    _write(spark, tmp_path, "benchmark", list(enumerate(items)), "item_id long, text string")
    _write(spark, tmp_path, "documents", list(enumerate(texts)), "doc_id long, text string")
    df = queries.QUERIES["document_benchmark_overlap"](spark, str(tmp_path))
    best = {k: max(apps.longest_common_substring(t, i)[2] for i in items[:5]) for k, t in enumerate(texts) if t is not None}
    assert {r.doc_id: r.len for r in df.collect()} == {k: n if n >= 24 else 0 for k, n in best.items()}


def test_former_queries_without_a_table_read_one(spark, sf):
    for name, table in (("hard_instances", "orders"), ("hard_single_one", "orders"), ("identified_strings", "embeddings"), ("identify_by_halving", "embeddings"), ("seeded_search_misses", "events")):
        assert any(f.endswith(f"/{table}.parquet") for f in queries.QUERIES[name](spark, sf).inputFiles()), name


def test_seeded_misses_fall_with_the_boost(spark, sf):
    missed = [r.missed for r in queries.QUERIES["seeded_search_misses"](spark, sf).orderBy("boost").collect()]
    assert len(missed) == 4 and missed[0] > missed[-1] and missed == sorted(missed, reverse=True)


def test_hard_strings_source(spark):
    from textfactor.sources import hard_strings

    hard_strings.register(spark)
    rows = spark.read.format("hard_strings").option("family", "single_one").option("n", "4").load().orderBy("case_no").collect()
    assert [r.text for r in rows] == ["1000", "0100", "0010", "0001", "0000"]


def test_plain_texts_are_cut_at_once_as_by_the_library():
    import numpy as np
    import public_tokenizers
    from tokenizers import Tokenizer

    from textfactor.llm import packing

    path = public_tokenizers.path(packing.DEFAULT_TOKENIZER)
    memo, library, rng = packing.ChunkIds(path), Tokenizer.from_file(path), random.Random(4)
    texts = ["", " ", "a_b __ x", "ÉÑ 12a3 Ÿ Ⱥ Ⱦ ×÷", "x\x0by\x0cz w", "--- == $5.20%\r\n[a]`~"]
    texts += ["".join(rng.choice("aB éŸȺ×_1.,-[ \n\t") for _ in range(rng.randrange(30))) for _ in range(500)]
    assert all(map(packing.PLAIN_TEXT.fullmatch, texts))
    for t in [*texts, "Don't <s> it", "İx ı", "a\x85b", "A b"]:
        assert np.frombuffer(memo.ids(t.encode()), f"<u{memo.width}").tolist() == library.encode(t, add_special_tokens=False).ids, t
    assert packing.TEXT_PARTS.findall("ab1_é×,".lower()) == packing.PARTS.findall("ab1_é×,") == ["ab", "1", "_", "é", "×,"]


def test_single_rows_are_looked_up_without_arrays(monkeypatch):
    from textfactor.kernels import index, suffix

    rng = random.Random(6)
    text = "".join(rng.choice("aab ") for _ in range(120))
    found, last = index.FmIndex(text), suffix.bwt(text)
    monkeypatch.setattr(index.np, "searchsorted", None)  # an array search for one row costs several times as much
    for c in set(last.tolist()):
        assert [found.runs.rank(c, r) for r in range(len(last) + 1)] == [last[:r].tolist().count(c) for r in range(len(last) + 1)]
    for p in ("a", "aa", "ab a", "b", "zz"):
        assert found.locate(p) == [i for i in range(len(text)) if text.startswith(p, i)]


def test_fragments_of_a_pair_are_looked_at_once(monkeypatch):
    from textfactor.kernels import solve

    seen, short = [], edit.ed_short
    monkeypatch.setattr(edit, "ed_short", lambda x, y: seen.append((x, y)) or short(x, y))
    rng, known = random.Random(9), edit.Fragments()
    x, y = ("".join(rng.choice("vcsep") for _ in range(50)) for _ in range(2))
    for base in (2, 3, 5):
        assert solve.solve(x, y, base=base, quota_scale=1e-2, known=known)[0] == _plain(x, y)[-1]
    assert seen and len(seen) == len(set(seen))
    for _ in range(300):
        x, y = _near(rng, rng.choice(["ab", "abcdé~"]))
        row, script = rng.randrange(len(x) + 1), edit.ed_diagonal_auto(x, y, script=True)[1]
        assert edit.Fragments().distance(x, y) == short(x, y) == _plain(x, y)[-1]
        assert edit.Fragments().crossing(x, y, row) == edit.first_column(script, row)


def test_equal_inputs_of_the_metered_sweeps_run_once(spark, sf, tmp_path):
    from textfactor.plans.rewrite import plan_text

    events = spark.read.parquet(f"{sf}/events.parquet").where("user_id < 4")
    twice = events.unionByName(events.selectExpr("event_id", "ts", "user_id + 10 as user_id", "event_type", "value", "props"))
    for name, table in (("one", events), ("two", twice)):
        table.write.parquet(f"{tmp_path}/{name}/events.parquet")
    for query, keys in (("edit_token_profile", ["base", "scale"]), ("edit_cost_profile", ["method", "bucket"]), ("grid_trade_off", ["tau", "mode"])):
        one, two = (queries.QUERIES[query](spark, f"{tmp_path}/{name}") for name in ("one", "two"))
        assert "copies" in plan_text(two)
        sums = {"pairs", "paused", "resumed", "killed", "restarts"}
        for a, b in zip(one.orderBy(*keys).collect(), two.orderBy(*keys).collect(), strict=True):
            for c in one.columns:
                assert a[c] == b[c] if isinstance(a[c], str) else abs(b[c] - a[c] * (2 if c in sums else 1)) <= 1e-9 * abs(b[c]), (query, c)


def test_prefix_ranks_are_shared_by_all_settings(monkeypatch):
    from textfactor.kernels import lz
    from textfactor.kernels.cost import Ledger

    rng = random.Random(5)
    for n in (0, 1, 30, 70):
        t = "".join(rng.choice("vcsep") for _ in range(n))
        ranks = lz.PrefixRanks(t)
        assert all(ranks.table[a][b] == next((k for k in range(min(a, b)) if t[a - k - 1] != t[b - k - 1]), min(a, b)) for a in range(n + 1) for b in range(n + 1))
        for tau in (1, 4, 16):
            for mode in ("linear", "sqrt_product", "merged"):
                own, shared = Ledger(), Ledger()
                first = lz.lz_end_grid(t, tau, mode=mode, ledger=own)
                assert first == lz.lz_end_grid(t, tau, mode=mode, ledger=shared, ranks=ranks) and own.row() == shared.row()
    arrays = [sorted(rng.sample(range(1000), k)) for k in (0, 1, 40, 300)]
    assert [lz.select_in_sorted(arrays, x, few) for few in (0, 24) for x in range(341)] == 2 * sorted(v for a in arrays for v in a)


def test_near_texts_by_brute_force(spark, tmp_path, monkeypatch):
    from textfactor import workload_queries as w

    rng, calls, exact = random.Random(12), [], edit.ed_short
    for _ in range(200):
        x, y = _near(rng, rng.choice(["ab", "abcdé~"]))
        d = _plain(x, y)[-1]
        assert all(edit.ed_near(x, y, k) == (d if d <= k else None) for k in (0, 1, 3, 30))
    monkeypatch.setattr(edit, "ed_short", lambda *a: calls.append(a) or exact(*a))
    x, y = ("".join(rng.choice(symbols) for _ in range(200)) for symbols in ("abcdefg", "hijklmn"))
    assert edit.ed_near(x, y, 20) is None and not calls
    head = "the same first words, then "
    texts = [head + "x" * n for n in (0, 1, 64, 65, 66, 130, 131, 0, 64)] + ["", "", "short", None, head[:24]]
    _write(spark, tmp_path, "documents", list(enumerate(texts)), "doc_id long, text string")
    got = {(r.a_id, r.b_id): r.distance for r in w.near_copy_distances(spark, str(tmp_path)).where("agree").collect()}
    assert got == w.brute_near_copies({k: v for k, v in enumerate(texts) if v is not None})


def test_unique_matches_of_many_pairs_by_suffix_order(monkeypatch):
    from textfactor.kernels import apps

    def words(n):
        return " ".join(rng.choice(["one", "two", "three", "fo", "é~"]) for _ in range(n))

    rng, plain = random.Random(2), apps.maximal_unique_matches
    for _ in range(12):
        base, texts = words(30), ["short"]
        for _ in range(5):
            y = list(base + (words(20) if rng.random() < 0.5 else ""))
            for _ in range(rng.randrange(5)):
                p = rng.randrange(len(y) + 1)
                y[p : p + rng.randrange(3)] = rng.choices("abc", k=rng.randrange(3))
            texts.append("".join(y) * rng.choice([1, 1, 2]))
        pairs = [(i, j) for i in range(6) for j in range(i + 1, 6)]
        for least in (4, 20):
            for x, y, found in apps.unique_match_sizes(texts, pairs, least):
                sizes = [m for _, _, m in plain(texts[x], texts[y], least)]
                assert found == (len(sizes), max(sizes, default=0))
    monkeypatch.setattr(apps, "maximal_unique_matches", None)  # a suffix order for each pair of texts that share their head only is what took the time
    texts = ["the same first words, then " + "".join(rng.choice(a) for _ in range(200)) for a in ("abc", "def", "ghi")]
    assert [m for *_, m in apps.unique_match_sizes(texts, [(0, 1), (1, 2)], 20)] == [(1, 27), (1, 27)]
    monkeypatch.setattr(apps, "_gram_prints", lambda codes, size: apps.np.zeros(max(0, len(codes) - size + 1), apps.np.uint64))  # every print collides
    monkeypatch.setattr(apps, "maximal_unique_matches", plain)
    assert [m for *_, m in apps.unique_match_sizes(texts, [(0, 1), (1, 2)], 20)] == [(1, 27), (1, 27)]


def _joined_texts(rng):
    word = lambda: "".join(rng.choice("abé日\0") for _ in range(rng.randrange(1, 4)))
    base = " ".join(word() for _ in range(60))
    texts = [base, base, base[5:], base.replace("a", "b"), "", "a" * 900, "ab" * 300 + "c", (base[:40] + "\n") * 9]
    return texts + [" ".join(word() for _ in range(rng.randrange(80))) for _ in range(30)]


def test_phrases_of_a_text_in_a_file_by_brute_force():
    from textfactor.kernels import external, lz

    rng = random.Random(3)
    for k in range(60):
        text = rng.choice(("", "é")).join(rng.choices(_joined_texts(rng), k=rng.randrange(1, 9))) or "x"
        file = external.TextFile(b"\1")
        file.add(text.encode())
        assert external.phrase_count(file.view(), (9, 200, 1 << 20)[k % 3]) == lz.lz_size(text)


def test_joined_texts_are_in_no_row(spark, tmp_path):
    from textfactor.kernels import lz
    from textfactor.operators.joined_text import phrase_counts
    from textfactor.plans.rewrite import plan_text

    texts = _joined_texts(random.Random(4))
    rows = [(k * 7 % 1009, t, ("x", "y", None)[k % 3]) for k, t in enumerate(texts)] + [(5000, None, "x"), (5001, "", "empty"), (5002, None, "none")]
    _write(spark, tmp_path, "documents", rows, "doc_id long, text string, source string")
    by_source = {s: [t for _, t, own in sorted(rows, key=lambda r: r[0]) if own == s and t is not None] for s in ("x", "y", None, "empty")}
    expected = {s: (len(j := "\1".join(ts)), z := lz.lz_size(j), len(j) / z if z else None) for s, ts in by_source.items()}
    found = queries.QUERIES["corpus_profile_by_source"](spark, str(tmp_path))
    assert "collect_list" not in plan_text(found)
    assert {r.source: tuple(r)[1:] for r in found.collect()} == expected
    dealt = phrase_counts(spark.read.parquet(f"{tmp_path}/documents.parquet"), "source", "doc_id", "text", range_size=64, least=300)
    assert {r.source: tuple(r)[1:] for r in dealt.collect()} == expected
