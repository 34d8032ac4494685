"""URL filter: rules by host and path, and a character language-model ratio for the rest.

Two variable-order Markov models (orders 0 to `order`, Witten-Bell smoothing, each order backing off to the one
below) are fitted to accepted and to rejected URLs. A URL's score is the difference of its log-likelihoods divided by its length.
The cut is calibrated on a held-out quarter of the labelled sample (largest balanced accuracy; midway between the scores next to it).
Labels are what the rules decide. At most `sample_urls` distinct labelled URLs of at most `sample_chars` characters per class are used, those with
the smallest hash; judging covers every row and whole URLs.

Cases: null, or no `://`: host and path are empty, no rule fits, and the empty text scores 0 against the cut like any other; if one class has no sample the
verdict is `allow`; repeated rows get a verdict each; a table without rows gives no rows.
"""

from __future__ import annotations

import math
from collections import defaultdict

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import bound_batches

# fixed values: (verdict, host, path)
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))


def host_path(url: Column) -> tuple[Column, Column]:
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), "(?s)^.*?://(.*)$", 1)
    raw = F.regexp_extract(rest, "(?s)^([^/?#]*)", 1)
    host = F.translate(raw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return host, F.regexp_extract(rest, "(?s)^[^/?#]*(/[^?#]*)", 1)


def with_rules(pages: DataFrame, url_col: str, rules=RULES) -> DataFrame:
    """host, path, rule and rule_verdict; the longest fitting rule wins."""
    host, path = host_path(F.col(url_col))
    out = pages.withColumn("host", host).withColumn("path", path)
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for decision, name, prefix in sorted(rules, key=lambda r: len(r[1] + r[2])):  # longer ones are tried first
        fits = ((F.col("host") == name) | F.col("host").endswith(f".{name}")) & F.col("path").startswith(prefix)
        rule, verdict = F.when(fits, f"{name}{prefix}").otherwise(rule), F.when(fits, decision).otherwise(verdict)
    return out.withColumn("rule", rule).withColumn("rule_verdict", verdict)


class VariableOrderModel:
    """Witten-Bell smoothed character model; contexts seen once are kept in the lower order only."""

    def __init__(self, texts: list[str], order: int = 5, alphabet: int = 256):
        counts: dict[str, dict[str, int]] = defaultdict(lambda: defaultdict(int))
        for t in texts:
            t = "\x02" + t + "\x03"
            for i in range(1, len(t)):
                for k in range(min(order, i) + 1):
                    counts[t[i - k : i]][t[i]] += 1
        self.order, self.floor = order, 1.0 / alphabet
        self.table = {c: (sum(n.values()), dict(n)) for c, n in counts.items() if not c or sum(n.values()) > 1}
        self.memo: dict[tuple[str, str], float] = {}

    def p(self, context: str, symbol: str) -> float:
        found = self.table.get(context)
        lower = self.p(context[1:], symbol) if context else self.floor
        if found is None:
            return lower
        total, after = found
        return (after.get(symbol, 0) + len(after) * lower) / (total + len(after))

    def log_p(self, text: str) -> float:
        t, out = "\x02" + text + "\x03", 0.0
        for i in range(1, len(t)):
            key = (t[max(0, i - self.order) : i], t[i])
            value = self.memo.get(key)
            if value is None:
                if len(self.memo) > 200_000:
                    self.memo.clear()
                value = self.memo[key] = math.log(self.p(*key))
            out += value
        return out


class UrlRatio:
    def __init__(self, accepted: list[str], rejected: list[str], order: int = 5):
        held = lambda x: [u for k, u in enumerate(x) if k % 4 == 3]
        fit = lambda x: [u for k, u in enumerate(x) if k % 4 != 3]
        self.ready = bool(accepted and rejected)
        self.cut = 0.0
        if self.ready:
            self.good, self.bad = VariableOrderModel(fit(accepted) or accepted, order), VariableOrderModel(fit(rejected) or rejected, order)
            a, b = sorted(map(self.score, held(accepted) or accepted)), sorted(map(self.score, held(rejected) or rejected))
            marks = sorted({*a, *b})
            cuts = [(x + y) / 2 for x, y in zip(marks, marks[1:], strict=False)] or [marks[0]]
            gain = [sum(x >= c for x in a) / len(a) + sum(x < c for x in b) / len(b) for c in cuts]
            # between the highest rejected and the lowest accepted score that the best cuts leave
            low, high = min(c for c, g in zip(cuts, gain, strict=True) if g == max(gain)), max(c for c, g in zip(cuts, gain, strict=True) if g == max(gain))
            self.cut = (low + high) / 2

    def score(self, url: str) -> float:
        return (self.good.log_p(url) - self.bad.log_p(url)) / (len(url) + 1)

    def verdict(self, url: str | None) -> tuple[str, float]:
        if not self.ready:
            return "allow", 0.0
        s = self.score(url or "")
        return ("allow" if s >= self.cut else "block"), s


def train(ruled: DataFrame, url_col: str, sample_urls: int = 3000, order: int = 5, sample_chars: int = 2000) -> UrlRatio:
    def sample(verdict: str) -> list[str]:
        urls = ruled.where((F.col("rule_verdict") == verdict) & (F.length(url_col) <= sample_chars)).select(F.col(url_col).alias("u")).distinct()
        return [r.u for r in urls.orderBy(F.xxhash64("u"), "u").limit(sample_urls).collect()]

    return UrlRatio(sample("allow"), sample("block"), order)


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", sample_urls: int = 3000, order: int = 5) -> DataFrame:
    """(id, host, path, rule, verdict, lm_score): rule verdicts first, the model's where no rule fits."""
    bound_batches(pages.sparkSession)
    slim = with_rules(pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url")), "url")
    sent = pages.sparkSession.sparkContext.broadcast(train(slim, "url", sample_urls, order))

    def look(batches):
        for batch in batches:
            found = [sent.value.verdict(u) for u in batch.column("url").to_pylist()]
            chosen = [r or v for r, (v, _) in zip(batch.column("rule_verdict").to_pylist(), found, strict=True)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("page_id", "host", "path", "rule")), pa.array(chosen, pa.string()), pa.array([s for _, s in found], pa.float64())], ["page_id", "host", "path", "rule", "verdict", "lm_score"])

    return slim.mapInArrow(look, "page_id long, host string, path string, rule string, verdict string, lm_score double")
