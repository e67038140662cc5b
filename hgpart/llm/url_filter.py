"""URL filtering: listed host/path rules first, then association rules mined by FP-growth from labelled URLs."""

from __future__ import annotations

import re
from itertools import product

import pandas as pd
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = "label=block"
SPLIT = re.compile(r"[^0-9A-Za-z]+")


def split_url(url: str | None) -> tuple[str, str]:
    """(host, path): host after the first ``://`` up to ``/ ? #`` with A-Z lower-cased, then the path up to ``? #``."""
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    host = re.match(r"[^/?#]*", rest).group()
    path = re.match(r"[^?#]*", rest[len(host):]).group()
    return host.translate({c: c + 32 for c in range(65, 91)}), path


def url_tokens(url: str | None) -> list[str]:
    """Distinct tokens: ``h:`` host labels, ``d:`` host suffixes, ``p:`` path words, ``q:`` query keys. Numbers only count as a class."""
    host, path = split_url(url)
    if not host:
        return []
    labels = host.split(".")
    found = [f"d:{'.'.join(labels[i:])}" for i in range(max(0, len(labels) - 3), len(labels))]
    found += [f"h:{w}" for label in labels for w in SPLIT.split(label) if w]
    found += [f"p:{'0' if w.isdigit() else w.lower()}" for w in SPLIT.split(path) if w]
    found += [f"q:{k}" for k in re.findall(r"[?&]([^=&#]+)", url)]
    return sorted(set(found))


class HostRules:
    """Longest rule (host, path prefix) that fits a host or one of its parents, by a hash index on hosts."""

    def __init__(self, rules: list[tuple[str, str]]):
        self.by_host: dict[str, list[tuple[str, str, str]]] = {}
        for rule, verdict in rules:
            host, _, path = rule.partition("/")
            self.by_host.setdefault(host, []).append((rule, "/" + path, verdict))

    def find(self, host: str, path: str) -> tuple[str, str] | None:
        best = None
        labels = host.split(".") if host else []
        for i in range(len(labels)):
            for rule, prefix, verdict in self.by_host.get(".".join(labels[i:]), ()):
                if path.startswith(prefix) and (best is None or len(rule) > len(best[0])):
                    best = (rule, verdict)
        return best


class TokenRules:
    """Inverted index of mined token sets, each listed under its rarest token."""

    def __init__(self, rules: list[tuple[list[str], float]]):
        often: dict[str, int] = {}
        for items, _ in rules:
            for t in items:
                often[t] = often.get(t, 0) + 1
        self.index: dict[str, list[tuple[frozenset, float]]] = {}
        for items, confidence in rules:
            self.index.setdefault(min(items, key=lambda t: (often[t], t)), []).append((frozenset(items), confidence))

    def matches(self, tokens: list[str]) -> list[tuple[frozenset, float]]:
        own = set(tokens)
        return [rule for t in tokens for rule in self.index.get(t, ()) if rule[0] <= own]

    def best(self, tokens: list[str]) -> tuple[str, float] | None:
        found = max(self.matches(tokens), key=lambda r: (r[1], -len(r[0]), sorted(r[0])), default=None)
        return found and (" & ".join(sorted(found[0])), found[1])


def mine_url_rules(labelled: DataFrame, url_col: str = "url", label_col: str = "blocked", min_support: float = 0.005, min_confidence: float = 0.8, min_count: int = 20) -> list[tuple[list[str], float]]:
    """Token sets that imply a block, mined by FP-growth: [(tokens, confidence)].

    ``labelled`` holds URLs and 0/1 labels; null labels or URLs are left out.
    Tokens below the least support are dropped first; mining sees all others of every URL. Tokens that occur in the same labelled URLs are
    mined as one and put back into the token sets found; those in every labelled URL change no count and are only rules of their
    own. Found token sets are counted over all labelled URLs by the
    inverted index that matching uses. A rule stays if its blocked URLs reach the support and its
    confidence ``min_confidence``, and no shorter kept rule that it contains is as sure.
    No labels, or none positive, give no rules.
    """
    tokens = F.pandas_udf(lambda s: s.map(url_tokens), "array<string>")
    rows = labelled.filter(F.col(url_col).isNotNull() & F.col(label_col).isNotNull()).select(tokens(url_col).alias("tokens"), F.col(label_col).cast("int").alias("y"))
    n, positive = rows.agg(F.count("*"), F.coalesce(F.sum("y"), F.lit(0))).first()
    if not n or not positive:
        return []
    support = min(1.0, max(min_support, min_count / n))
    mark = F.xxhash64("tokens")
    often = rows.select(F.explode("tokens").alias("t"), "y", mark.bitwiseAND(F.lit((1 << 31) - 1)).alias("low"), F.shiftrightunsigned(mark, 33).alias("high"))
    often = often.groupBy("t").agg(F.sum("y").alias("y"), F.count("*").alias("n"), F.sum("low").alias("low"), F.sum("high").alias("high")).filter(F.col("y") >= support * n)
    # at most tokens-per-URL / support rows, whatever n is
    same: dict[tuple, list[str]] = {}
    for r in sorted(often.collect()):
        same.setdefault((r["n"], r["y"], r["low"], r["high"]), []).append(r["t"])
    everywhere = [t for key, ts in same.items() if key[0] == n for t in ts]
    alike = {ts[0]: ts for key, ts in same.items() if key[0] < n}
    offer = F.pandas_udf(lambda s, y: pd.Series([[t for t in ts if t in alike] + [BLOCK] * int(v) for ts, v in zip(s, y, strict=True)]), "array<string>")
    items = rows.select(offer("tokens", "y").alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=min_confidence).fit(items)
    mined = model.associationRules.filter(F.array_contains("consequent", BLOCK)).select("antecedent").collect()
    found = [sorted(x) for r in mined for x in product(*(alike[t] for t in r["antecedent"]))]
    if positive >= min_confidence * n:
        found += [[t] for t in everywhere]
    if not found:
        return []
    index = TokenRules([(x, float(i)) for i, x in enumerate(found)])
    hits = F.pandas_udf(lambda s: s.map(lambda ts: [int(c) for _, c in index.matches(ts)]), "array<int>")
    exact = rows.select(F.explode(hits("tokens")).alias("rule"), "y").groupBy("rule").agg(F.count("*").alias("n"), F.sum("y").alias("y")).filter((F.col("y") >= support * n) & (F.col("y") / F.col("n") >= min_confidence)).collect()
    kept: list[tuple[list[str], float]] = []
    for r in sorted(exact, key=lambda r: (len(found[r["rule"]]), found[r["rule"]])):
        own, confidence = set(found[r["rule"]]), r["y"] / r["n"]
        if not any(set(k) <= own and c >= confidence for k, c in kept):
            kept.append((sorted(own), float(confidence)))
    return kept


def filter_urls(pages: DataFrame, mined: list[tuple[list[str], float]], listed: list[tuple[str, str]] = (), url_col: str = "url", default: str = "allow") -> DataFrame:
    """``pages`` without other columns than its own, plus host, path, rule, verdict, mined_rule, confidence.

    ``listed``: (``host/path``, verdict); the longest that fits decides. Where
    none fits, a mined rule whose tokens all occur blocks, else ``default``.
    Null URLs and those without ``://`` have empty host and path, fit no rule
    and get ``default``. Columns of the input with those six names are replaced.
    """
    host_rules, token_rules = HostRules(list(listed)), TokenRules(mined)

    def judge(urls: pd.Series) -> pd.DataFrame:
        out = []
        for url in urls:
            host, path = split_url(url)
            hit, found = host_rules.find(host, path), token_rules.best(url_tokens(url))
            rule, verdict = hit or (None, "block" if found else default)
            out.append((host, path, rule, verdict, *(found or (None, None))))
        return pd.DataFrame(out, columns=["host", "path", "rule", "verdict", "mined_rule", "confidence"]).astype({"confidence": "float64"})

    judged = F.pandas_udf(judge, "host string, path string, rule string, verdict string, mined_rule string, confidence double")
    names = ["host", "path", "rule", "verdict", "mined_rule", "confidence"]
    return pages.drop(*names).withColumn("_judged", judged(url_col)).select("*", *[F.col(f"_judged.{n}").alias(n) for n in names]).drop("_judged")
