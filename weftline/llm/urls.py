"""URL filter: host and path rules first, boosted trees on lexical features for the rest.

Rules name a host and the start of a path; the longest rule that fits decides.
URLs that no rule fits are judged by gradient-boosted trees over lexical
features (length, depth, digit ratio, entropy, parameter counts and smoothed
statistics of host suffixes), trained from labelled URLs on the driver.  The
sample for that is the ``FIT_ROWS`` labelled URLs of smallest hash, a documented
bound; scoring covers every row and needs no shuffle.

Defined cases.  A null URL or one without ``://`` has an empty host and path, fits
no rule and is judged by the trees like any other (as an empty text).  Without
labelled URLs, or with one class only, the trees give that class's rate.
Repeated rows are judged alike; extra columns pass through whatever their
names, those named like the results are replaced.
"""

import math
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ASCII_CAPITALS, ASCII_SMALL, column, free_name

#: Rules and what they decide.
RULES = {"net/": "block", "example.net/en/": "allow", "example.com/de/": "block", "org/fr/": "allow"}

FIT_ROWS = 20_000
MOST_RULES = 1_000


def host(url: Column) -> Column:
    found = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(found, ASCII_CAPITALS, ASCII_SMALL)


def path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def fitting_rule(url_host: Column, url_path: Column, rules: dict[str, str]) -> Column:
    """The longest rule that fits, else null; ties between equal lengths go by the alphabet."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"more than {MOST_RULES} rules make too long an expression")
    out = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(r), r)):
        own_host, slash, rest = rule.partition("/")
        fits = ((url_host == own_host) | F.endswith(url_host, F.lit(f".{own_host}"))) & F.startswith(url_path, F.lit(slash + rest))
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


NAMES = ("length", "host_length", "depth", "digit_ratio", "entropy", "n_params", "n_hyphens", "n_labels", "last_label", "last_two_labels")


def parts_of(url: str) -> tuple[str, str, str]:
    _, there, rest = url.partition("://")
    if not there:
        return "", "", ""
    cut = min((k for k in map(rest.find, "/?#") if k >= 0), default=len(rest))
    tail = rest[cut:]
    end = min((k for k in map(tail.find, "?#") if k >= 0), default=len(tail))
    return rest[:cut].lower(), tail[:end], tail[end:]


@dataclass
class Suffixes:
    """Smoothed block rates of the last one and two labels of hosts."""

    prior: float
    rates: dict[str, float]

    @classmethod
    def of(cls, hosts: list[str], y: np.ndarray, strength: float = 20.0) -> "Suffixes":
        prior = float(y.mean()) if len(y) else 0.5
        n, bad = Counter(), Counter()
        for h, v in zip(hosts, y.tolist()):
            for key in suffixes(h):
                n[key] += 1
                bad[key] += v
        return cls(prior, {k: (bad[k] + strength * prior) / (n[k] + strength) for k in n})

    def rate(self, key: str) -> float:
        return self.rates.get(key, self.prior)


def suffixes(url_host: str) -> tuple[str, str]:
    labels = url_host.rsplit(".", 2)
    return labels[-1], ".".join(labels[-2:])


def features(urls: list[str], known: Suffixes) -> np.ndarray:
    rows = []
    for url in urls:
        url_host, url_path, query = parts_of(url)
        n = len(url) or 1
        entropy = -sum(c / n * math.log2(c / n) for c in Counter(url).values())
        one, two = suffixes(url_host)
        rows.append((
            len(url), len(url_host), url_path.count("/"), sum(map(str.isdigit, url)) / n, entropy,
            query.count("="), url.count("-"), url_host.count("."), known.rate(one), known.rate(two),
        ))
    return np.array(rows, float).reshape(len(rows), len(NAMES))


@dataclass
class Trees:
    """Second-order boosted trees for the logistic loss over binned features."""

    base: float
    edges: list[np.ndarray]
    trees: list[list[tuple]]  # nodes in order of a heap: (feature, bin, value)

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, n_trees: int = 30, depth: int = 3, eta: float = 0.3, lam: float = 1.0, bins: int = 32) -> "Trees":
        rate = min(max(float(y.mean()) if len(y) else 0.0, 1e-3), 1 - 1e-3)
        model = cls(math.log(rate / (1 - rate)), [], [])
        if not len(y) or y.min() == y.max():
            return model
        model.edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
        b = model.binned(x)
        margin = np.full(len(y), model.base)
        for _ in range(n_trees):
            p = 1 / (1 + np.exp(-margin))
            tree = grow(b, p - y, p * (1 - p), depth, eta, lam, bins)
            margin += apply(tree, b)
            model.trees.append(tree)
        return model

    def binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, c, "left") for e, c in zip(self.edges, x.T)], 1)

    def probability(self, x: np.ndarray) -> np.ndarray:
        margin = np.full(len(x), self.base)
        if self.trees:
            b = self.binned(x)
            for tree in self.trees:
                margin += apply(tree, b)
        return 1 / (1 + np.exp(-margin))


def grow(b: np.ndarray, g: np.ndarray, h: np.ndarray, depth: int, eta: float, lam: float, bins: int) -> list[tuple]:
    tree = [(-1, 0, 0.0)] * (2 ** (depth + 1))
    members = {1: np.arange(len(g))}
    for node in range(1, 2 ** (depth + 1)):
        rows = members.pop(node, None)
        if rows is None:
            continue
        sum_g, sum_h = g[rows].sum(), h[rows].sum()
        best = (1e-9, -1, 0)
        if node < 2**depth and len(rows) > 1:
            for f in range(b.shape[1]):
                left_g = np.cumsum(np.bincount(b[rows, f], g[rows], bins))
                left_h = np.cumsum(np.bincount(b[rows, f], h[rows], bins))
                gain = left_g**2 / (left_h + lam) + (sum_g - left_g) ** 2 / (sum_h - left_h + lam) - sum_g**2 / (sum_h + lam)
                at = int(np.argmax(gain))
                if gain[at] > best[0]:
                    best = (gain[at], f, at)
        if best[1] < 0:
            tree[node] = (-1, 0, float(-eta * sum_g / (sum_h + lam)))
        else:
            tree[node] = (best[1], best[2], 0.0)
            goes_left = b[rows, best[1]] <= best[2]
            members[2 * node], members[2 * node + 1] = rows[goes_left], rows[~goes_left]
    return tree


def apply(tree: list[tuple], b: np.ndarray) -> np.ndarray:
    feature, cut, value = (np.array(c) for c in zip(*tree))
    node = np.ones(len(b), int)
    while (inner := feature[node] >= 0).any():
        f = np.maximum(feature[node], 0)
        below = 2 * node + (b[np.arange(len(b)), f] > cut[node])
        node = np.where(inner, below, node)
    return value[node]


@dataclass
class UrlModel:
    suffixes: Suffixes
    trees: Trees

    def block_probability(self, urls: list[str]) -> np.ndarray:
        return self.trees.probability(features(urls, self.suffixes))


def fit_urls(labelled: DataFrame, *, url: str = "url", label: str = "blocked", rows: int = FIT_ROWS) -> UrlModel:
    """Trains on the ``rows`` labelled URLs of smallest hash (ties by the URL).

    A threshold on the hash leaves few more rows than these to be sorted and
    sent, however many partitions there are; where it leaves too few, as one URL
    may make up many rows, it is raised.
    """
    known = labelled.filter(column(label).isNotNull()).select(F.coalesce(column(url), F.lit("")).alias("url"), column(label).cast("int").alias("y"))
    total, share, sample = known.count(), 0.0, []
    while total and len(sample) < min(rows, total) and share < 1:
        share = min(1.0, max(8 * share, 1.2 * rows / total))
        low = known if share == 1 else known.filter(F.xxhash64("url") < F.lit(int(share * 2**64) - 2**63))
        sample = low.orderBy(F.xxhash64("url"), "url", "y").limit(rows).collect()
    urls, y = [r["url"] for r in sample], np.array([r["y"] for r in sample], float)
    suffix_rates = Suffixes.of([parts_of(u)[0] for u in urls], y)
    return UrlModel(suffix_rates, Trees.fit(features(urls, suffix_rates), y))


RESULTS = ("host", "path", "rule", "block_probability", "verdict")


def filter_urls(pages: DataFrame, rules: dict[str, str] = RULES, model: UrlModel | None = None, *, url: str = "url", threshold: float = 0.5) -> DataFrame:
    """``pages`` with host, path, rule, block_probability and verdict.

    Without a model, one is trained on the URLs that rules decide.
    """
    names = {c: free_name(pages, f"url_{c}") for c in ("host", "path", "rule")}
    of = {c: column(name) for c, name in names.items()}
    probability = free_name(pages, "url_probability")
    told = pages.withColumns({names["host"]: host(column(url)), names["path"]: path(column(url))})
    told = told.withColumn(names["rule"], fitting_rule(of["host"], of["path"], rules))
    decided = F.lit(None).cast("string")
    for rule, verdict in rules.items():
        decided = F.when(of["rule"] == rule, F.lit(verdict)).otherwise(decided)
    if model is None:
        model = fit_urls(told.select(column(url).alias("url"), (decided == "block").alias("blocked")))
    fitted = model

    def block_probability(urls: pd.Series) -> pd.Series:
        return pd.Series(fitted.block_probability(urls.fillna("").tolist()))

    judged = told.withColumn(probability, F.pandas_udf(block_probability, "double")(column(url)))
    by_model = F.when(column(probability) > threshold, F.lit("block")).otherwise(F.lit("allow"))
    return judged.select(
        *[column(c) for c in pages.columns if c.lower() not in RESULTS],
        *[of[c].alias(c) for c in ("host", "path", "rule")],
        column(probability).alias("block_probability"), F.coalesce(decided, by_model).alias("verdict"),
    )
