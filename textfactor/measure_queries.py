"""Registered queries of primitives, measures, bounds and properties, over event sequences and test items."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from textfactor.kernels import anchor, apps, cost, edit, grammar, hard, index, lz, solve, suffix
from textfactor.operators import columns, rows
from textfactor.plans import rewrite
from textfactor.queries import ENDS_CTE, GREEDY, PAIRS, RUN_STEPS, RUNS, SEQ_TEXTS, SUFFIX_STEPS, SUFFIXES, TEXTS, greedy
from textfactor.registry import query, register
from textfactor.sources import tables as src

PAIR = ["a_id", "b_id"]


def common(side: str, a: str = "a", b: str = "b") -> str:
    """SQL for the longest common prefix (left) or suffix (right) of two strings."""
    return f"coalesce(list_max(list_filter(range(1, least(length({a}), length({b})) + 1), lambda l: {side}({a}, cast(l as int)) = {side}({b}, cast(l as int)))), 0)"


# --- primitives of the query model ---------------------------------------------------------------------------------------------
_N = "greatest(2, length(a))"


@query(f"""with {PAIRS} select a_id, b_id, a = b as equal, {common('left')} as lcp, {common('right')} as lcs, case when a < b then -1 when a > b then 1 else 0 end as lex,
case when reverse(a) < reverse(b) then -1 when reverse(a) > reverse(b) then 1 else 0 end as colex, instr(a, left(b, 3)) - 1 as first_hit, instr(a, 'c') - 1 as first_c, length(a) as reads,
cast(ceil(log2({_N})) as bigint) as repetitions, round(sqrt(length(a)) * ceil(log2({_N})), 6) as search_queries, round(sqrt(length(a)) * ceil(log2({_N})) * ceil(log2({_N})), 6) as search_time from pairs""")
def metered_primitives(spark, d):
    """Reads, searches, fragment equality, common prefixes and suffixes, both orders, pattern search, and what one search is charged."""

    def run(a, b):
        ledger = cost.Ledger()
        oracle = cost.SymbolOracle(a, ledger)
        symbols = [oracle.read(i) for i in range(len(oracle))]
        c = cost.grover_any([s == "c" for s in symbols], ledger, leftmost=True)
        one = cost.Ledger()
        one.search(len(a))
        return [(cost.frag_equal(a, b, ledger), cost.lcp_search(a, b, ledger), cost.lcs_search(a, b, ledger), cost.lex_cmp(a, b, ledger), cost.colex_cmp(a, b, ledger), cost.pattern_search(a, b[:3], ledger), -1 if c is None else c, ledger.oracle_reads, ledger.model.repetitions(len(a)), round(one.grover_queries, 6), round(one.grover_time, 6))]

    ddl = "equal boolean, lcp int, lcs int, lex int, colex int, first_hit int, first_c int, reads int, repetitions int, search_queries double, search_time double"
    return rows.explode_kernel(src.neighbour_pairs(spark, d), PAIR, ["a", "b"], ddl, run)


@query()
def seeded_search_misses(spark, d):
    """Share of searches for a purchase in the users' sequences that fail under seeded misses, by the boost: repetitions drive it down."""

    def run(user, s):
        out, places = [], [c == "p" for c in s]
        for boost in (0.1, 0.5, 1.0, 2.0):
            ledger = cost.Ledger(cost.CostModel(boost_c=boost, fail="seeded", seed=user))
            out.append((boost, 20, sum(cost.grover_any(places, ledger) is None for _ in range(20)), ledger.model.repetitions(len(s))))
        return out if any(places) else []

    found = rows.explode_kernel(src.event_sequences(spark, d), [], ["user_id", "s"], "boost double, searches int, missed int, repetitions int", run)
    return found.groupBy("boost").agg((F.sum("missed") / F.sum("searches")).alias("missed"), F.max("repetitions").alias("repetitions"))


# --- edit distance: definitions, properties, formulas --------------------------------------------------------------------------
@query(f"""with {PAIRS}, c as (select *, cast(ceil(length(a) / 2.0) as bigint) as x from pairs), spread as (select *, y from c, lateral (select unnest(range(0, length(b) + 1)) as y))
select a_id, b_id, cast(y as bigint) as y, levenshtein(left(a, cast(x as int)), left(b, cast(y as int))) + levenshtein(substr(a, cast(x as int) + 1), substr(b, cast(y as int) + 1)) = levenshtein(a, b) as is_anchor from spread""")
def edit_anchor_definition(spark, d):
    """Anchors by their definition: three tables for every place."""
    return rows.explode_kernel(src.neighbour_pairs(spark, d), PAIR, ["a", "b"], "y int, is_anchor boolean", lambda a, b: [(y, edit.is_anchor_exact(a, b, math.ceil(len(a) / 2), y)) for y in range(len(b) + 1)], heavy=True)


_ITEMS = "items as (select item_id, text as a, cast(length(text) // 3 as int) as p, left(text, cast(length(text) // 3 as int)) || '~' || substr(text, cast(length(text) // 3 as int) + 2) as b, cast(length(text) // 2 as int) as x from benchmark where length(text) > 3)"


def _edited_items(spark, d):
    """(item_id, a, b, x): test items with one symbol replaced, and a place in the middle."""
    items = src.table(spark, d, "benchmark").where("length(text) > 3").select("item_id", F.col("text").alias("a"), F.expr("cast(length(text) div 3 as int)").alias("p"), F.expr("cast(length(text) div 2 as int)").alias("x"))
    return items.select("item_id", "a", F.expr("concat(left(a, p), '~', substr(a, p + 2))").alias("b"), "x")


@query(f"with {_ITEMS} select item_id, cast(count(*) filter (where left(a, x) = left(b, cast(y as int)) or levenshtein(left(a, x), left(b, cast(y as int))) + levenshtein(substr(a, x + 1), substr(b, cast(y as int) + 1)) = 1) as bigint) as anchors from items, lateral (select unnest(range(greatest(0, x - 2), least(length(b), x + 2) + 1)) as y) group by item_id")
def anchor_locality(spark, d):
    """Anchors of the whole pair are those of a compressible window around the place; the window is what is tested. With one edit all lie within two symbols."""

    def run(a, b, x):
        lo, hi, _, _ = anchor.context_window(a, x, 1)
        inside = [y for y in range(len(b) + 1) if lo <= y <= hi + len(b) - len(a) and edit.is_anchor_exact(a[lo:hi], b[lo : hi + len(b) - len(a)], x - lo, y - lo)]
        return [(len(inside),)]

    return rows.explode_kernel(_edited_items(spark, d), ["item_id"], ["a", "b", "x"], "anchors int", run, heavy=True)


@query(f"with {_ITEMS} select item_id, x, cast(1 as bigint) as split_cost, true as passes from items where a <> b")
def edit_anchor_compressed(spark, d):
    """Anchors found and tested with distances of the window's phrases only; the two sides cost the one edit."""

    def run(a, b, x):
        ledger = cost.Ledger()
        y = anchor.find_anchor(a, b, 1, x, ledger=ledger, compressed=True)
        return [(x, y, anchor.test_anchor(a, b, 1, x, y, ledger=ledger, compressed=True))]

    found = rows.explode_kernel(_edited_items(spark, d).where("a <> b"), ["item_id", "a", "b"], ["a", "b", "x"], "x int, y int, passes boolean", run, heavy=True)
    cost_ = F.levenshtein(F.expr("left(a, x)"), F.expr("left(b, y)")) + F.levenshtein(F.expr("substr(a, x + 1)"), F.expr("substr(b, y + 1)"))
    return found.select("item_id", "x", cost_.alias("split_cost"), "passes")


@query(f"with {PAIRS} select a_id, b_id, levenshtein(a, b) as distance from pairs")
def edit_restart_in_three(spark, d):
    """Restarts with three parts a level."""
    return rows.edit_distance(src.neighbour_pairs(spark, d), "a", "b", PAIR, "restart_in_three").select(*PAIR, "distance")


_R = "greatest(2, ceil(5 * log2(greatest(2, n))))"


@query(f"""with {PAIRS}, p as (select *, length(a) as nx, length(b) as ny, greatest(length(a), length(b)) as n, levenshtein(a, b) as d from pairs)
select a_id, b_id, round(log10(10 * sqrt(d * (nx + ny)) * pow({_R}, 3) * pow(({_R} + 2) / {_R}, ceil(log2(nx)))), 6) as q_quota, round(log10(10 * d * d * pow({_R}, 9) * pow(({_R} + 2) / {_R}, ceil(log2(nx)))), 6) as t_quota from p where d > 0""")
def token_quotas(spark, d):
    """Token bounds of each pair's own distance, as powers of ten."""

    def run(a, b):
        n, distance = max(len(a), len(b)), edit.ed_diagonal_auto(a, b)
        q, t = solve.token_quota(len(a), len(b), distance, solve.Settings().r(n)) if distance else (0, 0)
        return [(round(math.log10(q), 6), round(math.log10(t), 6))] if distance else []

    return rows.explode_kernel(src.neighbour_pairs(spark, d), PAIR, ["a", "b"], "q_quota double, t_quota double", run)


@query(f"with {PAIRS} select a_id, b_id, levenshtein(a, b) as distance, true as adds_up, true as within from pairs where a <> b")
def edit_token_parts(spark, d):
    """Tokens in three parts (of the program that returns, of the call itself, of terminated programs): they add up and stay within their shares of the bound."""

    def run(a, b):
        if a == b:
            return []
        r = 5
        distance, _, g = solve.solve(a, b, base=r)
        q, t = solve.token_quota(len(a), len(b), distance, r)
        shares = (r / (r + 2), 0.1 / (r - 1), 1 / (r - 1))
        parts = (g.q_useful, g.q_own, g.q_terminated), (g.t_useful, g.t_own, g.t_terminated)
        adds = math.isclose(sum(parts[0]), g.q_tokens) and math.isclose(sum(parts[1]), g.t_tokens)
        return [(distance, adds, len(a) < 2 or all(p <= s * m * (1 + 1e-9) for part, m in zip(parts, (q, t), strict=True) for p, s in zip(part, shares, strict=True)))]

    return rows.explode_kernel(src.neighbour_pairs(spark, d), PAIR, ["a", "b"], "distance int, adds_up boolean, within boolean", run, heavy=True)


@query()
def edit_token_profile(spark, d):
    """The three parts of the tokens against the bound, for small bases of the thresholds and scaled quotas, where programs are paused and dropped.
    Pairs of equal texts are run once and count as often as they are there; all settings of a pair share what is known of its fragments."""
    settings = [(b, q) for b in (2, 3, 5) for q in (1e-4, 1e-2, 1.0)]

    def run(a, b):
        out, known = [], edit.Fragments()
        for base, scale in settings:
            distance, _, g = solve.solve(a, b, base=base, quota_scale=scale, known=known)
            q, _ = solve.token_quota(len(a), len(b), max(1, distance), base)
            total = max(1.0, g.q_tokens)
            out.append((base, scale, g.q_useful / total, g.q_own / total, g.q_terminated / total, g.q_tokens / q, g.paused, g.resumed, g.killed))
        return out

    pairs = src.neighbour_pairs(spark, d).groupBy("a", "b").agg(F.count(F.lit(1)).alias("copies"))
    found = rows.explode_kernel(pairs, ["copies"], ["a", "b"], "base int, scale double, useful double, own double, terminated double, of_bound double, paused long, resumed long, killed long", run, heavy=True)
    return found.groupBy("base", "scale").agg(*(columns.mean_of_copies(c) for c in ("useful", "own", "terminated", "of_bound")), *(F.sum(F.col(c) * F.col("copies")).alias(c) for c in ("paused", "resumed", "killed")))


@query(f"with {PAIRS} select a_id, b_id, round(levenshtein(a, b) * sqrt(length(a)), 6) as extension_queries, round(levenshtein(a, b) * sqrt(levenshtein(a, b) * length(a)), 6) as weighted_target, round(pow(length(a), 1.5), 6) as unbounded from pairs")
def edit_formulas(spark, d):
    """The formulas of the compared approaches at each pair's own distance."""

    def run(a, b):
        n, k = len(a), edit.ed_diagonal_auto(a, b)
        return [(round(cost.cost_lce_dp(n, k), 6), round(cost.cost_weighted_target(n, k), 6), round(cost.lower_bound("edit_unbounded", n=n), 6))]

    return rows.explode_kernel(src.neighbour_pairs(spark, d), PAIR, ["a", "b"], "extension_queries double, weighted_target double, unbounded double", run)


_LO, _HI = "cast(length(a) // 4 as int)", "cast(3 * length(a) // 4 as int)"
_WINDOW = f"substr(a, {_LO} + 1, {_HI} - {_LO}), substr(b, {_LO} + 1, greatest(0, {_HI} + length(b) - length(a) - {_LO}))"


@query(f"with {PAIRS} select a_id, b_id, levenshtein(a, b) as whole, levenshtein({_WINDOW}) as inside, levenshtein({_WINDOW}) <= levenshtein(a, b) as monotone from pairs")
def window_monotonicity(spark, d):
    """The distance of two windows with the same start, their ends apart by the difference in length, is no larger than the whole one."""

    def run(a, b):
        lo, hi = len(a) // 4, 3 * len(a) // 4
        whole, inside = edit.ed_diagonal_auto(a, b), edit.ed_diagonal_auto(a[lo:hi], b[lo : max(lo, hi + len(b) - len(a))])
        return [(whole, inside, inside <= whole)]

    return rows.explode_kernel(src.neighbour_pairs(spark, d), PAIR, ["a", "b"], "whole int, inside int, monotone boolean", run)


@query(f"with recursive {SEQ_TEXTS}, {greedy()}, z as (select id, count(*) as z from f group by id) select texts.id as user_id, z, levenshtein(left(t, length(t) - 5), substr(t, 6)) as shifted, 5 + 2 * levenshtein(left(t, length(t) - 5), substr(t, 6)) + 1 as bound, cast(0 as bigint) as violations from texts join z on z.id = texts.id where length(t) > 5")
def disjoint_alignments(spark, d):
    """A sequence against itself five symbols on: where the shifted alignment never meets the plain one, its cost bounds the phrases."""

    def run(s):
        if len(s) <= 5:
            return []
        target = s[5:]
        cost_, edits = edit.ed_diagonal_auto(s[:-5], target, script=True)
        apart = all(x != y + 5 for x, y in edit.path_of(len(target), len(target), edits))
        bound, z = edit.disjoint_bound(5, 0, cost_), lz.lz_size(s)
        return [(z, cost_, bound, int(apart and z > bound))]

    return rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "z int, shifted int, bound int, violations int", run)


# --- factorizations: baselines, measures, facts --------------------------------------------------------------------------------
_PHRASES_OF = GREEDY.format(texts=TEXTS, test="instr(t, substr(t, nxt, cast(l as int))) < nxt").replace("substr(t, nxt, m)", "substr(t, nxt, cast(m as int))")


@query(f"{_PHRASES_OF}, z as (select id, max(length(t)) as n, count(*) as z from f group by id) select id, n, z, n as reads, round(z * sqrt(n) * log2(greatest(2, n)), 6) as halving, round(sqrt(z * n), 6) as improved, cast(ceil(sqrt(n / z)) as bigint) as best_step from z")
def factor_baselines(spark, d):
    """Reading everything, identification by halving (both bounds), and the best grid step for the known phrase count."""

    def run(t):
        if not t:
            return []
        ledger = cost.Ledger()
        z, n = len(lz.read_all(t, ledger)), len(t)
        return [(n, z, ledger.oracle_reads, round(cost.cost_halving(n, z), 6), round(cost.cost_halving(n, z, improved=True), 6), rewrite.choose_tau(n, z))]

    return rows.explode_kernel(src.short_texts(spark, d), ["id"], ["t"], "n int, z int, reads int, halving double, improved double, best_step int", run)


@query(f"{_PHRASES_OF} select id, count(*) as z, round(sum(sqrt(len)) / sqrt(count(*) * max(length(t))), 6) as root_share, round(max(length(t)) / 4 + count(*) + 4 * count(*) + sum(sqrt(len)), 6) as work, cast(max(length(t)) as bigint) as n from f group by id")
def root_sums(spark, d):
    """Sum of the roots of phrase lengths against sqrt(zn), and the work formula at a step of 4."""
    p = rows.factorize(src.short_texts(spark, d), "t", ["id"], "lz77").groupBy("id").agg(F.count(F.lit(1)).alias("z"), F.sum(F.sqrt("len")).alias("roots"), F.sum("len").alias("n"))
    return p.select("id", "z", F.round(F.col("roots") / F.sqrt(F.col("z") * F.col("n")), 6).alias("root_share"), F.round(rewrite.work_formula(F.col("n"), F.col("z"), F.lit(4), F.col("roots")), 6).alias("work"), "n")


_VARIANTS = "variants as (select id, 'own' as kind, t from texts union all select id, 'reverse', reverse(t) from texts union all select id, 'half', left(t, cast(length(t) // 2 as int)) from texts union all select id, 'twice', t || t from texts union all select id, 'edited', left(t, cast(length(t) // 2 as int)) || 'z' || substr(t, cast(length(t) // 2 as int) + 2) from texts), named as (select id || ':' || kind as id, kind, t from variants)"


def _variants(s: str) -> list[tuple[str, str]]:
    m = len(s) // 2
    return [("own", s), ("reverse", s[::-1]), ("half", s[:m]), ("twice", s + s), ("edited", s[:m] + "z" + s[m + 1 :])]


@query(f"with recursive {SEQ_TEXTS}, {_VARIANTS}, {greedy(source='named')} select id, count(*) as z from f group by id")
def size_facts(spark, d):
    """Phrases of every sequence, its reverse, half, double, and with one symbol replaced."""
    found = rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "kind string, z int", lambda s: [(kind, lz.lz_size(t)) for kind, t in _variants(s) if t])
    return found.select(F.concat_ws(":", F.col("user_id").cast("string"), "kind").alias("id"), "z")


@query(f"with {SEQ_TEXTS}, {_VARIANTS}, grams as (select id, q, count(distinct substr(t, cast(p as int), cast(q as int))) as dq from named, lateral (select unnest(range(1, length(t) + 1)) as q), lateral (select unnest(range(1, length(t) - q + 2)) as p) group by id, q) select id, round(max(dq / q), 6) as delta from grams group by id")
def delta_properties(spark, d):
    """Substring complexity of the same variants: equal for the reverse, no larger for a part, at most doubled for the double, within one after an edit."""
    found = rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "kind string, delta double", lambda s: [(kind, round(suffix.delta(t), 6)) for kind, t in _variants(s) if t])
    return found.select(F.concat_ws(":", F.col("user_id").cast("string"), "kind").alias("id"), "delta")


@query(f"with {TEXTS} select id, t as expanded from texts where length(t) > 0")
def grammar_run_lengths(spark, d):
    """Texts through balanced grammars with run-length rules and back."""

    def run(t):
        rules = grammar.run_length_rules(grammar.grammar_from_lz(lz.lz77(t)))
        return [("".join(map(chr, grammar.expand_run_length(rules))),)] if t else []

    return rows.explode_kernel(src.short_texts(spark, d), ["id"], ["t"], "expanded string", run)


@query(f"""with recursive {SEQ_TEXTS}, {greedy()}, ends as (select id, list(start + len - 1) as ends from f group by id),
occ as (select texts.id, substr(t, cast(i as int), cast(l as int)) as g, len(list_filter(ends, lambda e: e >= i and e < i + l)) > 0 as held from texts join ends on ends.id = texts.id, lateral (select unnest(range(1, length(t) + 1)) as i), lateral (select unnest(range(1, length(t) - i + 2)) as l)),
open_ as (select id, count(*) filter (where not held) as n from (select id, g, bool_or(held) as held from occ group by id, g) group by id)
select ends.id as user_id, cast(len(ends) as bigint) as positions, n as unheld from ends join open_ on open_.id = ends.id""")
def attractor_positions(spark, d):
    """The last positions of phrases, and how many substrings have no occurrence that holds one of them."""

    def run(s):
        marks = grammar.attractor_from_lz(lz.lz77(s))
        held: dict[str, bool] = {}
        nxt = [min((m for m in marks if m >= i), default=len(s)) for i in range(len(s))]
        for i in range(len(s)):
            for j in range(i + 1, len(s) + 1):
                held[s[i:j]] = held.get(s[i:j], False) or nxt[i] < j
        return [(len(marks), sum(not v for v in held.values()))] if s else []

    return rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "positions int, unheld int", run)


_DELTA = "grams as (select id, q, count(distinct substr(t, cast(p as int), cast(q as int))) as dq from texts, lateral (select unnest(range(1, length(t) + 1)) as q), lateral (select unnest(range(1, length(t) - q + 2)) as p) group by id, q), deltas as (select id, max(dq / q) as delta from grams group by id)"
_LYNDON = "low as (select id, pos, rank, min(rank) over (partition by id order by pos rows between unbounded preceding and 1 preceding) as m from ranks), lyndon as (select id, count(*) as factors from low where m is null or rank < m group by id)"


@query(f"""with recursive {SEQ_TEXTS}, {greedy('f')}, {greedy('g', False)}, {ENDS_CTE.format(cands='ends')}, {RUN_STEPS}, {_DELTA}, {_LYNDON},
sizes as (select x.id, z, z_no, z_end, r, delta, factors from (select id, count(*) as z from f group by id) x join (select id, count(*) as z_no from g group by id) y on x.id = y.id join (select user_id, max(n) as z_end from ends_of group by user_id) e on e.user_id = x.id join (select id, count(distinct run_no) as r from numbered group by id) n on n.id = x.id join deltas on deltas.id = x.id join lyndon on lyndon.id = x.id)
select sizes.id as user_id, length(t) as n, cast(len(list_distinct(string_split(t, ''))) as bigint) as sigma, z, z_no, cast(z_end as bigint) as z_end, r, round(delta, 6) as delta, factors as lyndon, round(length(t) / z, 6) as n_over_z, round(length(t) / r, 6) as n_over_r,
round(r / (z * log2(length(t)) * log2(length(t))), 6) as r_ratio, round(z / (delta * log2(length(t))), 6) as z_ratio from sizes join texts on texts.id = sizes.id""")
def text_measures(spark, d):
    """All size measures of a text and their ratios to the bounds."""
    p = rows.compress_profile(src.event_sequences(spark, d), "s", ["user_id"])
    return p.select("user_id", "n", "sigma", "z", "z_no", "z_end", "r", F.round("delta", 6).alias("delta"), "lyndon", *(F.round(c, 6).alias(c) for c in ("n_over_z", "n_over_r", "r_ratio", "z_ratio")))


@query(f"with {RUNS} select id, count(*) - 1 as n, max(run_no)::bigint as r, 6 * max(run_no)::bigint as r_words, round(sqrt(max(run_no) * count(*)), 6) as modelled_queries from numbered group by id")
def index_words(spark, d):
    """Words of the run-sampled index, six a run, and the modelled construction cost."""
    found = rows.index_space(src.short_texts(spark, d).where("length(t) > 0"), "t", ["id"])
    return found.select("id", "n", "r", "r_words", F.round("modelled_queries", 6).alias("modelled_queries"))


_METHODS = ("dp", "diagonal", "diagonal_auto", "compressed", "restart", "ideal", "anchor")


@query(f"with {PAIRS} select method, count(*) as pairs, cast(sum(levenshtein(a, b)) as bigint) as distances, cast(0 as bigint) as mismatches from pairs, (select unnest({list(_METHODS)}) as method) group by method")
def method_mismatches(spark, d):
    """Accuracy: per method the number of pairs whose distance is not the exact one."""
    pairs = src.neighbour_pairs(spark, d).withColumn("exact", F.levenshtein("a", "b"))
    found = rows.edit_distances(pairs, "a", "b", [*PAIR, "exact"], [(m, None) for m in _METHODS])
    names = ["distance", *(f"distance_{k}" for k in range(2, len(_METHODS) + 1))]
    each = found.select("exact", F.expr(f"stack({len(names)}, {', '.join(f'{m!r}, {c}' for m, c in zip(_METHODS, names, strict=True))}) as (method, distance)"))
    return each.groupBy("method").agg(F.count(F.lit(1)).alias("pairs"), F.sum("distance").alias("distances"), F.count_if(F.col("distance") != F.col("exact")).alias("mismatches"))


# --- suffix structures ---------------------------------------------------------------------------------------------------------
@query(f"with {SEQ_TEXTS}, {SUFFIX_STEPS}, near as (select id, rank, suffix, lead(suffix, 3) over (partition by id order by rank) as below from ranks) select id as user_id, rank, {common('left', 'suffix', 'below')} as lcp from near where below is not null")
def lcp_of_rank_ranges(spark, d):
    """Common prefix of every four suffixes that follow each other."""

    def run(s):
        order = suffix.SuffixOrder(s)
        return [(r + 1, suffix.range_lcp(order, r, r + 3)) for r in range(order.n - 3)]

    return rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "rank int, lcp int", run)


@query(f"with {RUNS} select id, cast(run_no as bigint) - 1 as run_no, min(rank) as row_start, max(rank) as row_end from numbered group by id, run_no")
def runs_from_phrases(spark, d):
    """Run-length BWT computed from the phrases only."""

    def run(t):
        return [(n, a, b) for n, (_, a, b) in enumerate(index.rlbwt_from_lz(lz.lz77(t)).runs)] if t else []

    return rows.explode_kernel(src.short_texts(spark, d), ["id"], ["t"], "run_no int, row_start int, row_end int", run)


@query(f"""with {SEQ_TEXTS}, {SUFFIX_STEPS}, heads as (select id, left(suffix, cast(d as int)) as g, d as depth, min(rank) - 1 as lo, max(rank) - 1 as hi, count(distinct substr(suffix, cast(d as int) + 1, 1)) as ways from ranks, lateral (select unnest(range(1, length(suffix) + 1)) as d) group by 1, 2, 3)
select id as user_id, cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(depth as bigint) as depth from heads where hi > lo and ways > 1 union all select id, 0, length(t) - 1, 0 from texts where length(t) > 1""")
def suffix_tree_nodes(spark, d):
    """Inner nodes of the suffix tree as intervals of ranks with their depth."""
    return rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "lo int, hi int, depth int", lambda s: suffix.lcp_intervals(suffix.SuffixOrder(s)))


@query(f"""with {SEQ_TEXTS}, {RUN_STEPS}, sa as (select id, rank as row, pos - 1 as sa, run_no from numbered),
w as (select id, row, sa - lag(sa, 1) over o as d0, lead(sa, 1) over o - sa as d1, lag(run_no, 1) over o = lead(run_no, 1) over o as inside from sa window o as (partition by id order by row)),
seen as (select id, d0, d1, count(*) as n from w where d0 is not null and d1 is not null group by all)
select w.id as user_id, count(*) as windows, count(*) filter (where seen.n > 1) as repeated from w join seen on seen.id = w.id and seen.d0 = w.d0 and seen.d1 = w.d1 where inside and w.row > 1 group by w.id""")
def difference_copies(spark, d):
    """Two differences of the suffix array inside a run reappear elsewhere: counted by following the map to the run start that its image meets."""

    def run(s):
        if not s:
            return []
        found, n = index.SaIndex(s), len(s) + 1
        dsa, first = found.dsa().tolist(), set(found.runs.first.tolist())
        windows = [i for i in range(2, n - 1) if i not in first and i + 1 not in first]
        good = 0
        for i in windows:
            q = index.find_q(found, i, 2)
            good += q != i and dsa[q : q + 2] == dsa[i : i + 2]
        return [(len(windows), good)] if windows else []

    return rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "windows int, repeated int", run)


@query(f"with {SUFFIXES}, one as (select id, rank from ranks where pos = 1) select texts.id, cast(len(list_filter(range(1, length(t)), lambda p: substr(t, cast(p as int), 2) = left(t, 2))) as bigint) as leaves, cast(one.rank as bigint) as first_rank, {common('left', 't', 'substr(t, cast(length(t) // 2 as int) + 1)')} as extension from texts join one on one.id = texts.id where length(t) > 1")
def suffix_tree_queries(spark, d):
    """Leaves below a pattern's place, the rank of the whole text, and the extension of its start and middle, all by the level index."""

    def run(t):
        if len(t) < 2:
            return []
        found = index.SaIndex(t)
        return [(found.subtree(t[:2]), found.isa(0), found.lce(0, len(t) // 2))]

    return rows.explode_kernel(src.short_texts(spark, d), ["id"], ["t"], "leaves int, first_rank int, extension int", run)


@query(f"with {SEQ_TEXTS}, {SUFFIX_STEPS} select id as user_id, rank, cast(pos as bigint) as pos, cast(lead(pos) over (partition by id order by rank) as bigint) as next_pos from ranks qualify next_pos is not null")
def adjacent_ranks(spark, d):
    """Neighbours in suffix order by an equi-join on rank + 1."""
    ranks = columns.suffix_ranks(src.event_sequences(spark, d), "s", ["user_id"]).select("user_id", "rank", "pos")
    return ranks.join(ranks.select("user_id", (F.col("rank") - 1).alias("rank"), F.col("pos").alias("next_pos")), ["user_id", "rank"])


@query(f"with {SEQ_TEXTS}, g as (select id, substr(t, cast(i as int), cast(l as int)) as g, count(*) as n, min(i) as i from texts, lateral (select unnest(range(1, length(t) + 1)) as i), lateral (select unnest(range(1, length(t) - i + 2)) as l) group by 1, 2), m as (select id, max(length(g)) as len from g where n > 1 group by id) select m.id as user_id, cast(min(g.i) - 1 as bigint) as pos, cast(m.len as bigint) as len from m join g on g.id = m.id and length(g.g) = m.len and g.n > 1 group by m.id, m.len")
def answers_after_recovery(spark, d):
    """The longest repeat, asked of the phrases: the text is decoded first."""
    return rows.explode_kernel(src.event_sequences(spark, d), ["user_id"], ["s"], "pos int, len int", lambda s: [apps.with_recovered_text(lz.lz77(s), apps.longest_repeat)])


@query(f"with {SUFFIXES} select x.id, cast(x.pos - 1 as bigint) as i, cast(y.pos - 1 as bigint) as j, {common('left', 'x.suffix', 'y.suffix')} as extension from sufs x join sufs y on y.id = x.id and y.pos = x.pos + 7")
def dynamic_extensions(spark, d):
    """Extensions on a text that grows by the symbols and copies of its own factorization."""

    def run(t):
        grown = lz.DynamicLce()
        for _, size, source, code in lz.lz77(t):
            grown.push_copy(source, size) if source >= 0 else grown.push_symbol(code)
        return [(i, i + 7, grown.lce(i, i + 7)) for i in range(len(t) - 7)]

    return rows.explode_kernel(src.short_texts(spark, d), ["id"], ["t"], "i int, j int, extension int", run)


# --- hard inputs ---------------------------------------------------------------------------------------------------------------
@query("select case_no, cast(case when case_no < 24 then 1 else 0 end as bigint) as lcs, cast(case when case_no < 24 then 1 else 0 end as bigint) as ones, case when case_no < 24 then case_no else 0 end as last_suffix from (select distinct o_orderkey % 25 as case_no from orders)")
def hard_instances(spark, d):
    """What common substrings, 1-grams and one suffix-array query reveal about a string with at most a single one, whose place order keys name (none at the 25th)."""

    def run(case):
        pos = case if case < 24 else None
        a, b = hard.lcs_hard(24, pos)
        return [(apps.longest_common_substring(a, b)[2], hard.qgram_hard([c == "1" for c in a]), hard.index_hard(24, pos))]

    cases = src.table(spark, d, "orders").select((F.col("o_orderkey") % 25).alias("case_no")).distinct()
    return rows.explode_kernel(cases, ["case_no"], ["case_no"], "lcs int, ones int, last_suffix int", run)


def _threshold(name: str, bits, keep: list[str], t: int, sql: str) -> None:
    def run(spark, d):
        return rows.explode_kernel(bits(spark, d), keep, ["s"], "at_most boolean", lambda s: [(hard.threshold([c == "1" for c in s], t)[0],)])

    register(name, run, sql)


_threshold("threshold_quantity_by_supplier", lambda spark, d: src.ordered_string(src.table(spark, d, "lineitem"), ["l_suppkey"], list(src.LINE_ORDER), F.when(F.col("l_quantity") > 25, "1").otherwise("0")), ["l_suppkey"], 300, "select l_suppkey, count(*) filter (where l_quantity > 25) <= 300 as at_most from lineitem group by l_suppkey")
_threshold("threshold_embedding_signs", lambda spark, d: src.table(spark, d, "embeddings").select("vec_id", F.array_join(F.transform("embedding", lambda v: F.when(v > 0, "1").otherwise("0")), "").alias("s")), ["vec_id"], 32, "select vec_id, len(list_filter(embedding, lambda v: v > 0)) <= 32 as at_most from embeddings")


@query(f"with recursive texts as (select distinct s as id, s as t from (select array_to_string(list_transform(embedding[1:12], lambda v: case when v > 0 then '1' else '0' end), '') as s from embeddings where len(embedding) >= 12)), {greedy()} select z, count(*) as strings, true as all_found from (select id, count(*) as z from f group by id) group by z")
def identified_strings(spark, d):
    """Every string of the signs of a vector's first 12 components is recovered by majority and mismatch searches."""
    hidden = src.sign_strings(spark, d, 12)

    def run(s):
        return [(lz.lz_size(s), lz.identify_by_halving(s)[0] == s)]

    return rows.explode_kernel(hidden, [], ["s"], "z int, found boolean", run).groupBy("z").agg(F.count(F.lit(1)).alias("strings"), F.min("found").alias("all_found"))
