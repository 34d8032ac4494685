"""Operators over tables that hold one text or pair per row: an exact kernel runs inside the row's task, no shuffle is needed.

Null texts give null results in scalar columns and no rows in exploded ones. All frames are lazy and deterministic.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from textfactor import schema
from textfactor.kernels import anchor, apps, edit, grammar, index, lz, solve, suffix
from textfactor.kernels import batch as batch_edit
from textfactor.kernels.cost import Ledger
from textfactor.plans.rewrite import balance_by_cost, prefilter_pairs


def explode_kernel(df: DataFrame, keep: list[str], inputs: list[str], ddl: str, kernel, heavy: bool = False) -> DataFrame:
    """Rows keep + ddl: kernel(*inputs) returns the tuples of one input row. Output goes out in batches of a few thousand rows.

    heavy: the kernel's time outweighs moving its input, so rows are dealt by cost class over all partitions first."""
    kept = df.select(*keep, *(F.col(c).alias(f"in_{k}") for k, c in enumerate(inputs)))
    if heavy:
        kept = balance_by_cost(kept, F.coalesce(F.length(F.col("in_0").cast("string")), F.lit(0)))
    out_type = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields[: len(keep)]), ddl])
    names = [f"in_{k}" for k in range(len(inputs))]
    arrow = to_arrow_schema(StructType.fromDDL(out_type))

    def run(batches):
        for batch in batches:
            rows: list[tuple] = []
            columns = [batch.column(c).to_pylist() for c in [*keep, *names]]
            for values in zip(*columns, strict=True):
                own, given = values[: len(keep)], values[len(keep) :]
                if any(v is None for v in given):
                    continue
                rows += [(*own, *r) for r in kernel(*given)]
                if len(rows) >= 5000:
                    yield _batch(rows, arrow)
                    rows = []
            yield _batch(rows, arrow)

    return kept.mapInArrow(run, out_type)


def _batch(rows: list[tuple], arrow: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[]] * len(arrow)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, arrow, strict=True)], schema=arrow)


# --- edit distance -------------------------------------------------------------------------------------------------------------


def _distance(method: str, k: int | None, a, b, known: edit.Fragments | None = None) -> tuple:
    ledger, d = Ledger(), None
    if method == "dp":
        d = edit.ed_dp(a, b)
    elif method == "diagonal":
        d = edit.ed_diagonal(a, b, len(a) + len(b) if k is None else k)
    elif method == "diagonal_auto":
        d = edit.ed_diagonal_auto(a, b)
    elif method == "compressed":
        x, y = lz.lz77(a), lz.lz77(b)
        ledger.lz_calls = 2
        d = grammar.ed_compressed(x, y, len(a) + len(b) if k is None else k)
    elif method == "restart":
        d, ledger = solve.solve_restart(a, b, known=known)
    elif method == "restart_in_three":
        d, ledger = solve.solve_restart(a, b, branch=3, known=known)
    elif method == "ideal":
        d, ledger = solve.solve_ideal(a, b, known=known)
    elif method == "anchor":
        d, _, ledger = solve.solve(a, b, known=known)
    else:
        raise ValueError(f"no such method: {method}")
    d = -1 if d is None or (k is not None and d > k) else d
    return (d, *ledger.row().values())


def edit_distance(df: DataFrame, a: str, b: str, keep: list[str], method: str = "dp", k: int | None = None) -> DataFrame:
    """keep + distance (-1 above k) + cost columns. method: builtin (JVM only, no costs), dp, diagonal, diagonal_auto, compressed, restart, ideal, anchor."""
    if method == "builtin":
        d = F.levenshtein(a, b) if k is None else F.levenshtein(F.col(a), F.col(b), k)
        return df.select(*keep, d.alias("distance"))
    return edit_distances(df, a, b, keep, [(method, k)])


def edit_distances(df: DataFrame, a: str, b: str, keep: list[str], methods: list[tuple[str, int | None]]) -> DataFrame:
    """keep + distance and cost columns of the first (method, k) + distance_2, distance_3, ... of the others, in one pass over the pairs: pairs that are decided
    beforehand travel without their texts and are charged nothing."""
    easy = prefilter_pairs(df, a, b, methods[0][1] if len(methods) == 1 else None)
    text = lambda c: F.when(F.isnull("decided"), F.col(c)).otherwise(F.lit(""))
    sent = easy.select(*keep, text(a).alias("_a"), text(b).alias("_b"), F.coalesce("decided", F.lit(-2)).alias("_known"))
    nothing = tuple(type(v)(0) for v in Ledger().row().values())
    if all(m in ("dp", "diagonal_auto") for m, _ in methods):
        return _unmetered_distances(sent, keep, methods)

    def run(x, y, known):
        if known > -2:
            return [(known, *nothing, *(known for _ in methods[1:]))]
        shared = edit.Fragments()
        return [(*_distance(*methods[0], x, y, shared), *(_distance(*m, x, y, shared)[0] for m in methods[1:]))]

    others = "".join(f", distance_{k} int" for k in range(2, len(methods) + 1))
    return explode_kernel(sent, keep, ["_a", "_b", "_known"], f"distance int, {schema.COST}{others}", run, heavy=True)


def _unmetered_distances(sent: DataFrame, keep: list[str], methods: list[tuple[str, int | None]]) -> DataFrame:
    """edit_distances by the kernels that charge nothing, which take many pairs at a time."""
    sent = balance_by_cost(sent, F.coalesce(F.length("_a"), F.lit(0)))
    kernels = {"dp": batch_edit.ed_dp, "diagonal_auto": batch_edit.ed_diagonal_auto}
    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in sent.schema.fields[: len(keep)])
    out_type = f"{kept}, distance int, {schema.COST}" + "".join(f", distance_{k} int" for k in range(2, len(methods) + 1))
    arrow = to_arrow_schema(StructType.fromDDL(out_type))

    def run(batches):
        for whole in batches:
            for low in range(0, whole.num_rows, 20_000):
                batch = whole.slice(low, 20_000)
                batch = batch.filter(pc.and_(batch.column("_a").is_valid(), batch.column("_b").is_valid()))
                known = batch.column("_known").to_numpy(zero_copy_only=False)
                open_ = known == -2
                x, y = (batch.column(c).filter(pa.array(open_)).to_pylist() for c in ("_a", "_b"))
                found = []
                for method, k in methods:
                    d = known.astype(np.int32)
                    d[open_] = kernels[method](x, y)
                    if k is not None:
                        d[open_ & (d > k)] = -1
                    found.append(pa.array(d))
                charges = [pa.array(np.zeros(batch.num_rows), f.type, safe=False) for f in arrow][len(keep) + 1 : len(arrow) - len(methods) + 1]
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), found[0], *charges, *found[1:]], schema=arrow)

    return sent.mapInArrow(run, out_type)


def method_charges(df: DataFrame, a: str, b: str, keep: list[str], methods: tuple[str, ...]) -> DataFrame:
    """keep + a row per method: (method, n, distance, cost columns), n being the length of both texts. The methods of a pair share what is known of its
    fragments; equal texts are charged nothing."""
    nothing = tuple(type(v)(0) for v in Ledger().row().values())

    def run(x, y):
        shared = edit.Fragments()
        return [(m, len(x) + len(y), *((0, *nothing) if x == y else _distance(m, None, x, y, shared))) for m in methods]

    return explode_kernel(df, keep, [a, b], f"method string, n int, distance int, {schema.COST}", run, heavy=True)


def edit_script(df: DataFrame, a: str, b: str, keep: list[str], method: str = "anchor") -> DataFrame:
    """One row per edit in global 0-based positions."""

    def script(x, y):
        edits = solve.solve(x, y)[1] if method == "anchor" else edit.ed_diagonal_auto(x, y, script=True)[1]
        return [(n, *e) for n, e in enumerate(edits)]

    return explode_kernel(df, keep, [a, b], schema.EDIT, script, heavy=True)


def replay(df: DataFrame, a: str, b: str, keep: list[str]) -> DataFrame:
    """keep + (distance, deletes, inserts, substitutes, replays): the script's totals and whether it turns a into b."""

    def check(x, y):
        d, edits, _ = solve.solve(x, y)
        ops = [e[0] for e in edits]
        return [(d, ops.count("D"), ops.count("I"), ops.count("S"), edit.apply_edits(x, edits) == suffix.codes_of(y).tolist())]

    return explode_kernel(df, keep, [a, b], "distance int, deletes int, inserts int, substitutes int, replays boolean", check, heavy=True)


def alignment(df: DataFrame, a: str, b: str, keep: list[str]) -> DataFrame:
    """The optimal alignment's path, a row per step; op describes the step that ends here (null for the origin)."""

    def steps(x, y):
        path = edit.path_of(len(x), len(y), edit.ed_diagonal_auto(x, y, script=True)[1])
        return [(n, *p, op) for n, (p, op) in enumerate(zip(path, [None, *edit.align_ops(path, x, y)], strict=True))]

    return explode_kernel(df, keep, [a, b], schema.STEP, steps)


def align_cost(steps: DataFrame, keep: list[str]) -> DataFrame:
    return steps.groupBy(*keep).agg(F.sum(F.when(F.col("op").isin("I", "D", "S"), 1).otherwise(0)).alias("cost"))


def align_inverse(steps: DataFrame) -> DataFrame:
    op = F.when(F.col("op") == "I", "D").when(F.col("op") == "D", "I").otherwise(F.col("op"))
    return steps.select(*(c for c in steps.columns if c not in ("x", "y", "op")), F.col("y").alias("x"), F.col("x").alias("y"), op.alias("op"))


def align_product(df: DataFrame, a: str, b: str, c: str, keep: list[str]) -> DataFrame:
    """keep + (cost_ab, cost_bc, cost_product, valid) of the product of two optimal alignments."""

    def product(x, y, z):
        first = edit.path_of(len(x), len(y), edit.ed_diagonal_auto(x, y, script=True)[1])
        second = edit.path_of(len(y), len(z), edit.ed_diagonal_auto(y, z, script=True)[1])
        both = edit.align_product(first, second)
        return [(edit.align_cost(first, x, y), edit.align_cost(second, y, z), edit.align_cost(both, x, z), edit.align_is_valid(both, len(x), len(z)))]

    return explode_kernel(df, keep, [a, b, c], "cost_ab int, cost_bc int, cost_product int, valid boolean", product)


def anchors(df: DataFrame, a: str, b: str, pos: str, keep: list[str], k: int | None = None) -> DataFrame:
    """keep + (x, y, lo, hi, z_left, z_right): the anchor found at pos, with its window."""

    def find(x, y, p):
        bound = edit.ed_diagonal_auto(x, y) if k is None else k
        return [(p, anchor.find_anchor(x, y, bound, p), *anchor.context_window(x, p, bound))]

    return explode_kernel(df, keep, [a, b, pos], "x int, y int, lo int, hi int, z_left int, z_right int", find, heavy=True)


def test_anchors(df: DataFrame, a: str, b: str, pos: str, keep: list[str], k: int | None = None) -> DataFrame:
    """keep + (x, y, is_anchor) for every y of the pair."""

    def test(x, y, p):
        bound = edit.ed_diagonal_auto(x, y) if k is None else k
        return [(p, q, is_anchor) for q, is_anchor in enumerate(anchor.test_all_anchors(x, y, bound, p))]

    return explode_kernel(df, keep, [a, b, pos], "x int, y int, is_anchor boolean", test, heavy=True)


test_anchors.__test__ = False


def context_windows(df: DataFrame, text: str, pos: str, keep: list[str], k: int) -> DataFrame:
    return explode_kernel(df, keep, [text, pos], "lo int, hi int, z_left int, z_right int", lambda x, p: [anchor.context_window(x, p, k)])


# --- factorizations ------------------------------------------------------------------------------------------------------------


def phrases_of(scheme: str, text, tau: int | None = None, source: str = "leftmost", mode: str = "direct", engine: str = "direct") -> list[lz.Phrase]:
    if scheme == "lz77":
        return {"metered": lambda: lz.lz77_metered(text)[0], "read_all": lambda: lz.read_all(text, Ledger()), "direct": lambda: lz.lz77(text, source)}[engine]()
    if scheme == "nonoverlap":
        return {"direct": lambda: lz.lz77(text, source, overlap=False), "suffix_array": lambda: lz.lz_no_suffix_array(text), "sorted_prefix": lambda: lz.lz_no_sorted_prefix(text)}[engine]()
    if scheme == "lzend":
        return lz.lz_end(text)
    if scheme == "grid":
        if tau and mode == "direct":
            return lz.lz_end_direct(text, tau)
        return lz.lz_end_grid(text, tau, mode=mode) if tau else lz.lz_grid_auto(text)[0]
    raise ValueError(f"no such scheme: {scheme}")


def factorize(df: DataFrame, text: str, keep: list[str], scheme: str = "lz77", **options) -> DataFrame:
    """keep + phrase rows (0-based start and source; -1: none). scheme: lz77, nonoverlap, lzend, grid."""
    metered = options.get("engine", "direct") != "direct" or options.get("mode", "direct") != "direct"
    return explode_kernel(df, keep, [text], schema.PHRASE, lambda t: [(n, *p) for n, p in enumerate(phrases_of(scheme, t, **options))], heavy=metered)


def factor_sizes(df: DataFrame, text: str, keep: list[str], taus: tuple[int, ...] = (2,)) -> DataFrame:
    """keep + n, phrase counts of all schemes, and the sum of square roots over sqrt(zn)."""
    ddl = "n int, z int, z_no int, z_end int, " + ", ".join(f"z_grid_{t} int" for t in taus) + ", root_share double"

    def sizes(t):
        z = lz.lz77(t)
        share = sum(math.sqrt(p[1]) for p in z) / math.sqrt(len(z) * len(t)) if z else 0.0
        return [(len(t), len(z), lz.lz_size(t, overlap=False), len(lz.lz_end(t)), *(len(lz.lz_end_direct(t, tau)) for tau in taus), share)]

    return explode_kernel(df, keep, [text], ddl, sizes, heavy=True)


def grid_costs(df: DataFrame, text: str, keep: list[str], taus: tuple[int, ...], modes: tuple[str, ...] = ("linear", "sqrt_product", "merged")) -> DataFrame:
    """keep + (tau, mode, n, phrases, formula, cost columns): the trade-off n/tau + tau z + sqrt(zn) next to metered charges."""

    def run(t):
        out, ranks = [], lz.PrefixRanks(t)
        for tau in taus:
            for mode in modes:
                ledger = Ledger()
                z = len(lz.lz_end_grid(t, tau, mode=mode, ledger=ledger, ranks=ranks))
                out.append((tau, mode, len(t), z, len(t) / tau + tau * z + math.sqrt(z * len(t)), *ledger.row().values()))
        return out

    return explode_kernel(df, keep, [text], f"tau int, mode string, n int, phrases int, formula double, {schema.COST}", run, heavy=True)


def guess_doubling(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (n, phrases, guess, tau, restarts, comparisons, searches, reads, bound_ratio) of the doubling of the unknown phrase count."""

    def run(t):
        ledger = Ledger()
        out, guess, tau = lz.lz_grid_auto(t, ledger)
        z = max(1, lz.lz_size(t))
        return [(len(t), len(out), guess, tau, ledger.restarts, ledger.comparisons, ledger.grover_queries, ledger.oracle_reads, ledger.oracle_reads / math.sqrt(z * max(1, len(t))))]

    return explode_kernel(df, keep, [text], "n int, phrases int, guess int, tau int, restarts long, comparisons long, searches double, reads long, bound_ratio double", run, heavy=True)


def check_factorization(df: DataFrame, text: str, keep: list[str], scheme: str, **options) -> DataFrame:
    """keep + (phrases, valid, decoded, converted): whether the scheme's result is LZ77-like, the text it decodes to, and the number of greedy phrases it converts to
    (-1 if those are not the greedy ones)."""

    def check(t):
        p = phrases_of(scheme, t, **options)
        greedy = lz.to_lz77(p)
        same = [x[:2] for x in greedy] == [x[:2] for x in lz.lz77(t)]
        return [(len(p), lz.is_lz77_like(p, t), "".join(map(chr, lz.decode(p))), len(greedy) if same else -1)]

    return explode_kernel(df, keep, [text], "phrases int, valid boolean, decoded string, converted int", check, heavy=True)


def grammar_rules(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    return explode_kernel(df, keep, [text], schema.RULE, lambda t: grammar.rules_of(grammar.grammar_from_lz(lz.lz77(t))))


def grammar_sizes(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (n, phrases, rules, depth, expands)."""

    def run(t):
        p = lz.lz77(t)
        g = grammar.grammar_from_lz(p)
        return [(len(t), len(p), len(grammar.rules_of(g)), g.height[g.root] if p else 0, g.expand() == suffix.codes_of(t).tolist())]

    return explode_kernel(df, keep, [text], "n int, phrases int, rules int, depth int, expands boolean", run)


def compress_profile(df: DataFrame, text: str, keep: list[str], tau: int = 4) -> DataFrame:
    """keep + n, sigma, z, z_no, z_end, z_grid, r, delta, lyndon, zlib and bz2 sizes, and ratios to the bounds."""

    def run(t):
        import bz2
        import zlib

        n, raw = len(t), t.encode()
        z, r, d = lz.lz_size(t), suffix.run_count(t), suffix.delta(t)
        log = math.log2(max(2, n))
        return [(n, len(set(t)), z, lz.lz_size(t, overlap=False), len(lz.lz_end(t)), len(lz.lz_end_direct(t, tau)), r, d, len(apps.lyndon(t)), len(zlib.compress(raw)), len(bz2.compress(raw)), n / z if z else 0.0, n / r if r else 0.0, r / (z * log * log) if z else 0.0, z / (d * log) if d else 0.0)]

    ddl = "n int, sigma int, z int, z_no int, z_end int, z_grid int, r int, delta double, lyndon int, zlib_bytes int, bz2_bytes int, n_over_z double, n_over_r double, r_ratio double, z_ratio double"
    return explode_kernel(df, keep, [text], ddl, run, heavy=True)


# --- suffix structures and indexes ---------------------------------------------------------------------------------------------


def suffix_table(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """keep + (pos, rank, lcp, bwt, lf): one row per suffix of text + sentinel; bwt holds code points, -1 for the sentinel."""

    def rows(t):
        codes = suffix.with_sentinel(suffix.codes_of(t))
        order = suffix.SuffixOrder(codes)
        last = codes[order.sa - 1]
        back = [int(c) - 2 if c else -1 for c in last]
        return list(zip(order.sa.tolist(), range(order.n), order.lcp().tolist(), back, suffix.lf_mapping(last).tolist(), strict=True))

    return explode_kernel(df, keep, [text], schema.SUFFIX, rows)


def bwt_runs(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    def rows(t):
        runs = index.BwtRuns(suffix.bwt(t))
        return [(n, c - 2 if c else -1, a, b, int(runs.lf_first[n])) for n, (c, a, b) in enumerate(runs.runs)]

    return explode_kernel(df, keep, [text], schema.RUN, rows)


def lf_power(df: DataFrame, text: str, keep: list[str], tau: int) -> DataFrame:
    def rows(t):
        p = index.lf_power(index.BwtRuns(suffix.bwt(t)), tau)
        ends = [*p.start[1:].tolist(), p.n]
        return [(int(s), e - 1, int(i), int(i + e - 1 - s), int(c)) for s, e, i, c in zip(p.start, ends, p.image, p.sym, strict=True)]

    return explode_kernel(df, keep, [text], schema.INTERVAL, rows)


def index_space(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    names = "n int, r int, tau int, lf_intervals int, r_words int, sa_words int, fm_words int, modelled_queries double, levels int"
    return explode_kernel(df, keep, [text], names, lambda t: [tuple(index.build_indexes_metered(t).values())])


def pattern_occurrences(df: DataFrame, text: str, patterns: str | list[str], keep: list[str], kind: str = "run") -> DataFrame:
    """keep + (pattern, n, pos) for an array column of patterns, or for one list for all rows, which goes with the task: n occurrences, one row each (pos null
    where there is none; a list's patterns have no such row). kind: run or fm."""
    single = isinstance(patterns, str)
    if not single and kind == "fm":
        return _occurrences_of_all(df, text, patterns, keep)

    def rows(t, wanted=None):
        found = index.RIndex(t) if kind == "run" else index.FmIndex(t)
        out = []
        for p in wanted if single else patterns:
            at = found.locate(p)
            out += [(p, len(at), v) for v in at] or ([(p, 0, None)] if single else [])
        return out

    return explode_kernel(df, keep, [text, patterns] if single else [text], "pattern string, n int, pos int", rows, heavy=True)


def _occurrences_of_all(df: DataFrame, text: str, patterns: list[str], keep: list[str]) -> DataFrame:
    """All patterns of a list at once in the sampled index of each text; results leave as arrays."""
    kept = balance_by_cost(df.where(F.col(text).isNotNull()).select(*keep, F.col(text).alias("in_0")), F.length("in_0"))
    out_type = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields[: len(keep)]), "pattern string, n int, pos int"])
    arrow = to_arrow_schema(StructType.fromDDL(out_type))

    def run(batches):
        ready, names = index.Patterns(patterns), pa.array(patterns, pa.string())
        for batch in batches:
            source, which, n, pos, held = [], [], [], [], 0

            def out(batch=batch):
                row = pa.array(np.concatenate(source))
                columns = [*(batch.column(c).take(row) for c in keep), names.take(pa.array(np.concatenate(which))), pa.array(np.concatenate(n)), pa.array(np.concatenate(pos))]
                return pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip(columns, arrow, strict=True)], schema=arrow)

            for k, t in enumerate(batch.column("in_0").to_pylist()):
                count, at = index.FmIndex(t).locate_all(ready)
                owner = np.repeat(np.arange(len(count)), count)
                for held_in, values in ((source, np.full(len(at), k)), (which, owner), (n, count[owner]), (pos, at)):
                    held_in.append(values)
                held += len(at)
                if held >= 50_000:
                    yield out()
                    source, which, n, pos, held = [], [], [], [], 0
            if held:
                yield out()

    return kept.mapInArrow(run, out_type)


def sa_lookup(df: DataFrame, text: str, keep: list[str], kind: str = "level") -> DataFrame:
    """keep + (i, sa, isa) of every row, answered by the level index or the slow index rather than from the array."""

    def rows(t):
        found = index.SaIndex(t) if kind == "level" else index.SlowIndex(t)
        return [(i, found.sa(i), found.isa(i)) for i in range(found.n)]

    return explode_kernel(df, keep, [text], "i int, sa int, isa int", rows)


# --- applications --------------------------------------------------------------------------------------------------------------


def longest_common_substring(df: DataFrame, a: str, b: str, keep: list[str]) -> DataFrame:
    return explode_kernel(df, keep, [a, b], "a_pos int, b_pos int, len int", lambda x, y: [apps.longest_common_substring(x, y)])


def maximal_unique_matches(df: DataFrame, a: str, b: str, keep: list[str], least: int = 1) -> DataFrame:
    return explode_kernel(df, keep, [a, b], "a_pos int, b_pos int, len int", lambda x, y: apps.maximal_unique_matches(x, y, least))


def longest_repeat(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    return explode_kernel(df, keep, [text], "pos int, len int", lambda t: [apps.longest_repeat(t)])


def shortest_unique(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    return explode_kernel(df, keep, [text], "pos int, len int", lambda t: [apps.shortest_unique(t)])


def lyndon_factors(df: DataFrame, text: str, keep: list[str]) -> DataFrame:
    return explode_kernel(df, keep, [text], "factor_no int, start int, len int", lambda t: [(n, *f) for n, f in enumerate(apps.lyndon(t))])


def qgram_freq(df: DataFrame, text: str, keep: list[str], q: int) -> DataFrame:
    return explode_kernel(df, keep, [text], "gram string, n int", lambda t: [(t[i : i + q], n) for i, n in apps.qgram_freq(t, q)])


def hamming_distance(df: DataFrame, a: str, b: str, keep: list[str]) -> DataFrame:
    """JVM only: positions that differ in two strings of equal length (null otherwise)."""
    differ = F.zip_with(F.split(a, ""), F.split(b, ""), lambda x, y: F.when(x == y, 0).otherwise(1))
    return df.select(*keep, F.when(F.length(a) == F.length(b), F.aggregate(differ, F.lit(0), lambda s, v: s + v)).alias("distance"))


