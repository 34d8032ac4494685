"""The SQL surface: register_all(spark) makes every function below callable by name."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from textfactor.functions.rowwise import each
from textfactor.kernels import anchor, apps, edit, index, lz, solve, suffix


@pandas_udf("int")
def tf_edit_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    return each(lambda x, y: edit.ed_diagonal_auto(x, y), a, b)


@pandas_udf("int")
def tf_edit_bounded(a: pd.Series, b: pd.Series, k: pd.Series) -> pd.Series:
    def bounded(x, y, m):
        d = edit.ed_diagonal(x, y, int(m))
        return -1 if d is None else d

    return each(bounded, a, b, k)


@pandas_udf("int")
def tf_lz_size(t: pd.Series) -> pd.Series:
    return each(lz.lz_size, t)


@pandas_udf("int")
def tf_lz_end_size(t: pd.Series) -> pd.Series:
    return each(lambda x: len(lz.lz_end(x)), t)


@pandas_udf("int")
def tf_grid_size(t: pd.Series, tau: pd.Series) -> pd.Series:
    return each(lambda x, k: len(lz.lz_end_grid(x, int(k))), t, tau)


@pandas_udf("double")
def tf_delta(t: pd.Series) -> pd.Series:
    return each(suffix.delta, t)


@pandas_udf("int")
def tf_bwt_runs(t: pd.Series) -> pd.Series:
    return each(suffix.run_count, t)


@pandas_udf("int")
def tf_lce(t: pd.Series, i: pd.Series, j: pd.Series) -> pd.Series:
    return each(lambda x, p, q: suffix.SuffixOrder(x).lce(int(p), int(q)), t, i, j)


@pandas_udf("int")
def tf_lcs_len(a: pd.Series, b: pd.Series) -> pd.Series:
    return each(lambda x, y: apps.longest_common_substring(x, y)[2], a, b)


@pandas_udf("boolean")
def tf_is_anchor(a: pd.Series, b: pd.Series, x: pd.Series, y: pd.Series) -> pd.Series:
    return each(lambda s, t, p, q: anchor.test_anchor(s, t, edit.ed_diagonal_auto(s, t), int(p), int(q)), a, b, x, y)


@pandas_udf("distance int, edits int, q_tokens double, t_tokens double")
def tf_solve(a: pd.Series, b: pd.Series) -> pd.DataFrame:
    rows = []
    for x, y in zip(a, b, strict=True):
        if x is None or y is None:
            rows.append((None, None, None, None))
        else:
            d, edits, ledger = solve.solve(x, y)
            rows.append((d, len(edits), ledger.q_tokens, ledger.t_tokens))
    return pd.DataFrame(rows, columns=["distance", "edits", "q_tokens", "t_tokens"])


@pandas_udf("n int, z int, r int, delta double")
def tf_profile(t: pd.Series) -> pd.DataFrame:
    rows = [(None,) * 4 if x is None else (len(x), lz.lz_size(x), suffix.run_count(x), suffix.delta(x)) for x in t]
    return pd.DataFrame(rows, columns=["n", "z", "r", "delta"])


@pandas_udf("int")
def tf_concat_size(t: pd.Series) -> int:
    """Aggregate: phrases of the group's texts joined by a separator, in sorted order."""
    return lz.lz_size("\x01".join(sorted(x for x in t if x is not None)))


@pandas_udf("int")
def tf_lcs_group(t: pd.Series) -> int:
    """Aggregate: longest substring that the group's first two texts (sorted) share; 0 for fewer."""
    some = sorted(x for x in t if x is not None)
    return apps.longest_common_substring(some[0], some[1])[2] if len(some) > 1 else 0


@udtf(returnType="phrase_no int, start int, len int, src int")
class TfPhrases:
    def eval(self, text: str, scheme: str, tau: int):
        from textfactor.operators.rows import phrases_of

        if text is not None:
            for n, (start, size, src, _) in enumerate(phrases_of(scheme, text, tau=tau or None) if scheme == "grid" else phrases_of(scheme, text)):
                yield n, start, size, src


@udtf(returnType="pos int, rank int, lcp int")
class TfSuffixes:
    def eval(self, text: str):
        if text:
            order = suffix.SuffixOrder(text)
            for r, (p, m) in enumerate(zip(order.sa.tolist(), order.lcp().tolist(), strict=True)):
                yield p, r, m


@udtf(returnType="run_no int, sym string, row_start int, row_end int")
class TfRuns:
    def eval(self, text: str):
        if text is not None:
            for n, (c, a, b) in enumerate(suffix.runs_of(suffix.bwt(text))):
                yield n, chr(c - 2) if c else "", a, b


@udtf(returnType="step int, op string, x int, y int, sym string")
class TfEdits:
    def eval(self, a: str, b: str):
        if a is not None and b is not None:
            for n, (op, x, y, s) in enumerate(solve.solve(a, b)[1]):
                yield n, op, x, y, chr(s) if s >= 0 else None


@udtf(returnType="a_pos int, b_pos int, len int")
class TfMums:
    def eval(self, a: str, b: str):
        if a is not None and b is not None:
            yield from apps.maximal_unique_matches(a, b)


@udtf(returnType="factor_no int, start int, len int")
class TfLyndon:
    def eval(self, text: str):
        if text is not None:
            for n, (start, size) in enumerate(apps.lyndon(text)):
                yield n, start, size


@udtf(returnType="pos int")
class TfLocate:
    def eval(self, text: str, pattern: str):
        if text is not None and pattern:
            for p in index.RIndex(text).locate(pattern):
                yield (p,)


SCALARS = (tf_edit_distance, tf_edit_bounded, tf_lz_size, tf_lz_end_size, tf_grid_size, tf_delta, tf_bwt_runs, tf_lce, tf_lcs_len, tf_is_anchor, tf_solve, tf_profile, tf_concat_size, tf_lcs_group)
TABLES = {"tf_phrases": TfPhrases, "tf_suffixes": TfSuffixes, "tf_runs": TfRuns, "tf_edits": TfEdits, "tf_mums": TfMums, "tf_lyndon": TfLyndon, "tf_locate": TfLocate}


def register_all(spark: SparkSession) -> None:
    for function in SCALARS:
        spark.udf.register(function.__name__, function)
    for name, function in TABLES.items():
        spark.udtf.register(name, function)
