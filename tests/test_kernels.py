"""Kernels against naive definitions, worked examples and identities."""

import itertools
import random

import numpy as np
import pytest

from textfactor.kernels import anchor, apps, cost, edit, grammar, hard, index, lz, solve, suffix


def texts(seed, count, longest, alphabet="abc"):
    rng = random.Random(seed)
    return ["".join(rng.choice(alphabet[: rng.randint(1, len(alphabet))]) for _ in range(rng.randint(0, longest))) for _ in range(count)]


EDGES = ["", "a", "aaaa", "abcd", "a$b$", "é\nüé", "ab" * 20]


def greedy(s, allowed):
    """Lengths of a factorization that takes the longest allowed phrase, or one fresh symbol."""
    i, out = 0, []
    while i < len(s):
        m = next((m for m in range(len(s) - i, 0, -1) if allowed(s, i, m, out)), 0)
        out.append(max(1, m))
        i += out[-1]
    return out


def overlapping(s, i, m, out):
    return s.find(s[i : i + m], 0, i + m - 1) >= 0


def apart(s, i, m, out):
    return s.find(s[i : i + m], 0, i) >= 0


def ending(tau=None):
    def allowed(s, i, m, out):
        ends = set(np.cumsum(out).tolist()) | ({k for k in range(1, i + 1) if (k - 1) % tau == 0} if tau else set())
        return any(e >= m and s[e - m : e] == s[i : i + m] for e in ends)

    return allowed


def lengths(phrases):
    return [p[1] for p in phrases]


BINARY = ["".join(x) for n in range(8) for x in itertools.product("01", repeat=n)]


def test_worked_examples():
    p = lz.lz77("abacabcabcaaaab", source="rightmost")
    assert [(a + 1, n) for a, n, _, _ in p] == [(1, 1), (2, 1), (3, 1), (4, 1), (5, 2), (7, 5), (12, 3), (15, 1)]
    assert [s + 1 for _, _, s, _ in p if s >= 0] == [1, 1, 4, 11, 9]
    assert lengths(lz.lz_end("00010011011")) == [1, 1, 1, 1, 3, 1, 3]
    assert lengths(lz.lz_end_grid("00010011011", 2)) == [1, 1, 1, 1, 3, 2, 1, 1]
    assert apps.longest_common_substring("a", "a")[2] == 1


@pytest.mark.parametrize("pool", [BINARY, texts(2, 60, 24), EDGES])
def test_factorizations(pool):
    for s in pool:
        full, no, end = greedy(s, overlapping), greedy(s, apart), greedy(s, ending())
        assert lengths(lz.lz77(s)) == full and lz.is_lz77_like(lz.lz77(s), s)
        assert lengths(lz.lz77(s, overlap=False)) == lengths(lz.lz_no_sorted_prefix(s)) == lengths(lz.lz_no_suffix_array(s)) == no
        assert lengths(lz.lz_end(s)) == end
        assert len(full) <= len(no) <= len(end)
        for tau in (1, 2, 3, len(s) + 1):
            want = greedy(s, ending(tau))
            assert lengths(lz.lz_end_direct(s, tau)) == want
            for mode in ("linear", "sqrt_product", "merged"):
                assert lengths(lz.lz_end_grid(s, tau, mode=mode)) == want
        assert lengths(lz.lz_end_grid(s, 1)) == no
        metered, ledger = lz.lz77_metered(s)
        assert lengths(metered) == full and "".join(map(chr, lz.decode(metered))) == s
        assert suffix.delta(s) <= len(full) or not s


def test_suffix_array_engine_holds_an_order():
    from textfactor.kernels.cost import Ledger

    for text in ("abaababaabaab" * 5, "aaaa", "", "abcabcabd"):
        got = lz.lz_no_suffix_array(text, ledger := Ledger())
        assert [p[:2] for p in got] == [p[:2] for p in lz.lz77(text, overlap=False)] and lz.is_lz77_like(got, text)
        assert all(src < 0 or src + size <= start for start, size, src, _ in got)
        assert not text or ledger.comparisons >= len(text)  # each read position is put in its place


def test_grid_modes_charge_their_scans():
    from textfactor.kernels.cost import Ledger

    for size in (64, 128):  # one long phrase: variant 1 reads all of its symbols, variant 2 about the root of them
        state = lz.GridState("ab" * size + "c" + "ab" * size, 4, ledger=(linear := Ledger()), mode="linear")
        state.advance(0, 2 * size + 1)
        h = state.far(2 * size + 1, 4 * size)
        assert h is not None and linear.oracle_reads >= h - (2 * size + 1)
        assert linear.oracle_reads <= 2 * size + 6  # the reach is reused: tau more at most, and not tau times the length
        other = lz.GridState("ab" * size + "c" + "ab" * size, 4, ledger=(root := Ledger()), mode="sqrt_product")
        other.advance(0, 2 * size + 1)
        assert other.far(2 * size + 1, 4 * size) == h and root.grover_calls > 1
    merged, own = Ledger(), Ledger()
    assert lz.lz_grid_auto("ab" * 20, merged) == lz.lz_grid_auto("ab" * 20, own, mode="merged") and merged.row() == own.row()
    assert lz.lz_grid_auto("ab" * 20, mode="linear") == lz.lz_grid_auto("ab" * 20)


def test_selection_and_identification():
    rng = random.Random(1)
    for _ in range(100):
        arrays = [sorted(rng.choices(range(9), k=rng.randint(0, 6))) for _ in range(4)]
        merged = sorted(sum(arrays, []))
        assert [lz.select_in_sorted(arrays, x) for x in range(len(merged))] == merged
    for s in ("0110100", "0000000", "1011011"):
        assert lz.identify_by_halving(s)[0] == s


def test_suffix_order():
    for s in texts(1, 150, 14) + EDGES:
        o, n = suffix.SuffixOrder(s), len(s)
        assert o.sa.tolist() == sorted(range(n), key=lambda i: s[i:])
        for i, j in itertools.product(range(n), repeat=2):
            k = next((k for k in range(n) if i + k >= n or j + k >= n or s[i + k] != s[j + k]), n - max(i, j))
            assert o.lce(i, j) == (n - i if i == j else k)
            assert o.lce(np.array([i]), np.array([j]))[0] == o.lce(i, j)
        assert "".join(map(chr, suffix.inverse_bwt(suffix.bwt(s)))) == s
        d = suffix.distinct_counts(o)
        assert all(d[q] == len({s[i : i + q] for i in range(n - q + 1)}) for q in range(1, n + 1))


def table_distance(a, b):
    row = list(range(len(b) + 1))
    for i, c in enumerate(a):
        new = [i + 1]
        for j, e in enumerate(b):
            new.append(min(row[j + 1] + 1, new[j] + 1, row[j] + (c != e)))
        row = new
    return row[-1]


def test_edit_distances_and_alignments():
    pool = texts(5, 60, 12) + EDGES
    for x, y, z in zip(pool, pool[1:], pool[2:], strict=False):
        d = table_distance(x, y)
        assert edit.ed_dp(x, y) == d
        for ext in (None, edit.Extensions(x, y), edit.DirectExtensions(x, y)):
            assert edit.ed_diagonal(x, y, d, ext) == d and (d == 0 or edit.ed_diagonal(x, y, d - 1, ext) is None)
        dd, edits = edit.ed_diagonal_auto(x, y, script=True)
        assert dd == len(edits) == d and "".join(map(chr, edit.apply_edits(x, edits))) == y
        path = edit.path_of(len(x), len(y), edits)
        assert edit.align_is_valid(path, len(x), len(y)) and edit.align_cost(path, x, y) == d == edit.align_cost(edit.align_inverse(path), y, x)
        e, more = edit.ed_diagonal_auto(y, z, script=True)
        product = edit.align_product(path, edit.path_of(len(y), len(z), more))
        assert edit.align_is_valid(product, len(x), len(z)) and edit.align_cost(product, x, z) <= d + e
        assert grammar.ed_compressed(lz.lz77(x), lz.lz77(y), d) == d


def test_solver_is_exact_under_pauses():
    rng, seen = random.Random(5), [0, 0, 0]
    for _ in range(60):
        x = "".join(rng.choice("ab") for _ in range(rng.randint(1, 50)))
        y = list(x)
        for _ in range(rng.randint(0, 8)):
            p = rng.randrange(len(y) + 1)
            y[p : p + rng.randint(0, 1)] = rng.choice(["", "a", "b", "c"])
        y = "".join(y)
        d = edit.ed_dp(x, y)
        for base, scale, const in ((2, 1e-2, 1), (3, 1e-4, 6), (5, 1.0, 6)):
            got, edits, ledger = solve.solve(x, y, base=base, quota_scale=scale, const=const)
            assert got == d == len(edits) and "".join(map(chr, edit.apply_edits(x, edits))) == y
            seen = [seen[0] + ledger.paused, seen[1] + ledger.resumed, seen[2] + ledger.killed]
            if base == 5 and d:
                q, t = solve.token_quota(len(x), len(y), d, 5)
                assert ledger.q_tokens <= q and ledger.t_tokens <= t
        assert solve.solve_ideal(x, y)[0] == d == solve.solve_restart(x, y)[0] == solve.solve_restart(x, y, branch=3)[0]
    assert all(seen)
    assert solve.solve([5, 7, 9], [7, 9, 9])[0] == 2


def test_anchors():
    pool = [t for t in texts(9, 40, 9, "ab") if t]
    for x, y in zip(pool, pool[1:], strict=False):
        k = edit.ed_dp(x, y)
        for p in range(len(x) + 1):
            assert edit.is_anchor_exact(x, y, p, anchor.find_anchor(x, y, k, p))
            for q in range(len(y) + 1):
                assert anchor.test_anchor(x, y, k, p, q) == edit.is_anchor_exact(x, y, p, q)
    assert anchor.test_anchor("ab", "ab", 1, 1, None) is False


def occurrences(s, p):
    return [i for i in range(len(s) - len(p) + 1) if s[i : i + len(p)] == p]


def test_indexes():
    for s in [t for t in texts(4, 60, 24) + EDGES if t]:
        fm, run, slow, level = index.FmIndex(s, 3), index.RIndex(s), index.SlowIndex(s, 4), index.SaIndex(s)
        sa, lf = fm.order.sa.tolist(), suffix.lf_mapping(fm.last)
        for row, v in enumerate(sa):
            assert fm.sa(row) == slow.sa(row) == level.sa(row) == v and slow.isa(v) == level.isa(v) == row
        at = np.arange(fm.n)
        for tau in (1, 2, 4, 8):
            table, w = index.lf_power(fm.runs, tau), at
            for _ in range(tau):
                w = lf[w]
            assert (table.apply(at) == w).all() and len(table) <= tau * len(fm.runs.runs)
        for p in {s[i : i + m] for i in range(len(s)) for m in (1, 2, 4)} | {"zz", "ca"}:
            want = occurrences(s, p)
            assert fm.count(p) == run.count(p) == level.subtree(p) == len(want) and fm.locate(p) == run.locate(p) == want


def test_applications():
    for s, t in zip(texts(7, 50, 16), texts(8, 50, 12), strict=True):
        grams = {s[i:j] for i in range(len(s)) for j in range(i + 1, len(s) + 1)}
        a, b, m = apps.longest_common_substring(s, t)
        assert m == max((len(g) for g in grams if g in t), default=0) and s[a : a + m] == t[b : b + m]
        unique = [(s.find(g), t.find(g), len(g)) for g in grams if len(occurrences(s, g)) == 1 == len(occurrences(t, g))]
        grown = [(i, j, n) for i, j, n in unique if not (i and j and s[i - 1] == t[j - 1]) and not (i + n < len(s) and j + n < len(t) and s[i + n] == t[j + n])]
        assert apps.maximal_unique_matches(s, t) == sorted(grown)
        assert apps.lyndon(s) == apps.duval(s)
        assert {s[i : i + 2]: n for i, n in apps.qgram_freq(s, 2)} == dict(apps.qgram_counter(s, 2))
        assert apps.longest_repeat(s)[1] == max((len(g) for g in grams if len(occurrences(s, g)) > 1), default=0)
        if s:
            assert apps.shortest_unique(s)[1] == min(len(g) for g in grams if len(occurrences(s, g)) == 1)


def test_hard_inputs():
    for n in range(1, 8):
        for bits in itertools.product([0, 1], repeat=n):
            ones, s = sum(bits), "".join(map(str, bits))
            x = hard.size_reduction(bits)
            assert len(x) == 4 * n + 2 and lz.lz_size(x) == hard.expected_size(ones)
            z, r = hard.threshold_bounds(ones)
            assert lz.lz_size(s) <= z and suffix.run_count(s, False) <= r
            assert all(hard.threshold(bits, t)[0] == (ones <= t) for t in range(3))
            assert edit.ed_dp(bits, [0] * n) == ones
    assert lz.lz_size(hard.single_one(9, None)) == 2
    assert all(3 <= lz.lz_size(hard.single_one(9, p)) <= 5 for p in range(9))
    assert hard.median_from_phrases(lz.lz77([5, 3, 9])) == 5


def test_grammars():
    for s in texts(3, 40, 30) + EDGES:
        g = grammar.grammar_from_lz(lz.lz77(s))
        assert "".join(map(chr, g.expand())) == s
        assert "".join(map(chr, g.extract(1, 3))) == s[1:4]
    g = grammar.grammar_from_lz(lz.lz77("ab" * 5000))
    assert len(grammar.rules_of(g)) < 60 and g.height[g.root] < 30


def test_metered_primitives():
    ledger = cost.Ledger()
    assert cost.lcp_search("abcabd", "abcabc", ledger) == 5 and cost.lex_cmp("ab", "abc", ledger) == -1 and cost.colex_cmp("ba", "ab", ledger) == -1
    assert cost.hamming("abc", "abd") == 1 and cost.min_rotation("bca") == 2 and ledger.grover_queries > 0
    misses = []
    for c in (0.1, 0.5, 2):
        seeded = cost.Ledger(cost.CostModel(boost_c=c, fail="seeded"))
        misses.append(sum(cost.grover_any(np.arange(16) == 3, seeded) is None for _ in range(300)))
    assert misses[0] > misses[1] > misses[2]
    assert cost.SymbolOracle("ab", ledger).read(1) == "b" and ledger.oracle_reads == 1


def test_dynamic_order_and_extensions():
    for s in texts(21, 40, 24) + EDGES:
        grown = lz.DynamicLce()
        for _, size, source, code in lz.lz77(s):
            if source >= 0:
                grown.push_copy(source, size)
            else:
                grown.push_symbol(code)
        assert "".join(map(chr, grown.codes)) == s
        for i, j in itertools.product(range(len(s)), repeat=2):
            want = next((k for k in range(len(s)) if max(i, j) + k >= len(s) or s[i + k] != s[j + k]), len(s) - max(i, j))
            assert grown.lce(i, j) == want
            back = next((k for k in range(min(i, j)) if s[i - k - 1] != s[j - k - 1]), min(i, j))
            assert grown.lcs(i, j) == back
        for tau in (1, 3):
            for mode in ("linear", "sqrt_product", "merged"):
                ledger = cost.Ledger()
                assert lengths(lz.lz_end_grid(s, tau, mode=mode, order="dynamic", ledger=ledger)) == lengths(lz.lz_end_grid(s, tau, mode=mode))
        assert lengths(lz.lz_end_grid(s, "opt")) == lengths(lz.lz_end_grid(s, max(1, int(np.ceil(np.sqrt(max(1, len(s)) / max(1, lz.lz_size(s))))))))
        assert lz.lz_size(s) == len(lz.lz77(s)) and lz.lz_size(s, overlap=False) == len(lz.lz77(s, overlap=False))
        ledger = cost.Ledger()
        assert lz.read_all(s, ledger) == lz.lz77(s) and ledger.oracle_reads == len(s)


def test_token_parts():
    rng, dropped = random.Random(8), 0
    for _ in range(40):
        x = "".join(rng.choice("ab") for _ in range(rng.randint(2, 60)))
        y = "".join(rng.choice("ab") if rng.random() < 0.2 else c for c in x)
        if x == y:
            continue
        for base, scale in ((5, 1.0), (2, 1e-3), (3, 1e-4)):
            d, _, g = solve.solve(x, y, base=base, quota_scale=scale, const=1 if base == 2 else 6)
            assert abs(g.q_useful + g.q_own + g.q_terminated - g.q_tokens) <= 1e-9 * g.q_tokens and abs(g.t_useful + g.t_own + g.t_terminated - g.t_tokens) <= 1e-9 * g.t_tokens
            dropped += g.q_terminated > 0
            if base == 5:
                q, t = solve.token_quota(len(x), len(y), d, 5)
                for part, share in (("useful", 5 / 7), ("own", 0.1 / 4), ("terminated", 1 / 4)):
                    assert getattr(g, f"q_{part}") <= share * q and getattr(g, f"t_{part}") <= share * t
    assert dropped


def test_anchors_from_phrases():
    pool = [t for t in texts(19, 20, 8, "ab") if t]
    for x, y in zip(pool, pool[1:], strict=False):
        k = edit.ed_dp(x, y)
        for p in range(len(x) + 1):
            assert edit.is_anchor_exact(x, y, p, anchor.find_anchor(x, y, k, p, compressed=True))
            for q in range(len(y) + 1):
                assert anchor.test_anchor(x, y, k, p, q, compressed=True) == anchor.test_anchor(x, y, k, p, q)


def test_windows_are_monotone_and_complexity_is_stable():
    rng = random.Random(13)
    for s, t in zip(texts(31, 40, 20), texts(32, 40, 20), strict=True):
        if s:
            i, j = sorted((rng.randint(0, len(s)), rng.randint(0, len(s))))
            assert edit.ed_dp(s[i:j], t[i : max(i, j + len(t) - len(s))]) <= edit.ed_dp(s, t) or j + len(t) - len(s) < i
            p = rng.randrange(len(s))
            changed = s[:p] + "z" + s[p + 1 :]
            assert suffix.delta(s) == suffix.delta(s[::-1]) and suffix.delta(s[i:j]) <= suffix.delta(s) and abs(suffix.delta(changed) - suffix.delta(s)) <= 1 + 1e-9
            assert suffix.delta(s + t) <= suffix.delta(s) + suffix.delta(t) + 1e-9 or suffix.delta(s + t) <= suffix.delta(s) + suffix.delta(t) + 1
            assert suffix.delta(s) <= lz.lz_size(s)


def test_run_length_rules_and_runs_from_phrases():
    for s in texts(23, 40, 30) + EDGES:
        g = grammar.grammar_from_lz(lz.lz77(s))
        rules = grammar.run_length_rules(g)
        assert "".join(map(chr, grammar.expand_run_length(rules))) == s and len(rules) <= len(grammar.rules_of(g))
        assert index.rlbwt_from_lz(lz.lz77(s)).runs == suffix.runs_of(suffix.bwt(s))
    assert len(grammar.run_length_rules(grammar.grammar_from_lz(lz.lz77("a" * 4096)))) <= 3


def test_level_index_answers_from_phrases():
    for s in [t for t in texts(14, 20, 20) if t]:
        found = index.SaIndex(s)
        for i, j in itertools.product(range(len(s)), repeat=2):
            assert found.lce(i, j) == suffix.SuffixOrder(s).lce(i, j)
