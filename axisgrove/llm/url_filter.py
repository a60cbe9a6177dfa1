"""URL filter: host and path rules, and gradient-boosted trees on lexical features.

A rule decides where one fits; every other URL is judged by trees that were trained with
logistic loss on labelled URLs. Training takes at most ``MAX_TRAINING`` URLs and runs on
the driver; the model is a few kilobytes and travels inside the scoring function.
"""

from __future__ import annotations

import math
import random
import re
from collections import Counter
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.llm.common import keeping, table

#: Rule (host and path) to verdict.
RULES = {"net/": "block", "example.net/en/": "allow", "example.com/de/": "block", "org/fr/": "allow"}
#: Most labelled URLs that are used for training.
MAX_TRAINING = 20_000

FEATURES = (
    "length", "host_length", "depth", "digit_ratio", "host_digit_ratio", "entropy", "host_entropy", "parameters", "longest_parameter",
    "hyphens", "labels", "longest_label", "escapes", "port_or_user", "address", "suffix_odds", "word_odds",
)


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path; both empty for null or without ``://``."""
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    cut = re.search(r"[/?#]", rest)
    host = rest if cut is None else rest[: cut.start()]
    path = "" if cut is None else re.split(r"[?#]", rest[cut.start() :], maxsplit=1)[0]
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host), path


def matching_rule(host: str, path: str, rules: dict[str, str]) -> str | None:
    """The longest rule whose host is the URL's or a parent domain of it, and whose path starts the URL's."""
    best = None
    for rule in rules:
        rule_host, slash, rest = rule.partition("/")
        if (host == rule_host or host.endswith("." + rule_host)) and path.startswith(slash + rest) and (best is None or len(rule) > len(best)):
            best = rule
    return best


def _entropy(s: str) -> float:
    n = len(s)
    return -sum(c / n * math.log2(c / n) for c in Counter(s).values()) if n else 0.0


def host_words(host: str) -> list[str]:
    return re.findall(r"[a-z]{2,}", host.rpartition(".")[0])


def features(url: str | None, suffix_odds: dict[str, float], word_odds: dict[str, float]) -> list[float]:
    url = url or ""
    host, path = split_url(url)
    query = url.split("#", 1)[0].partition("?")[2]
    params = [p for p in query.split("&") if p]
    labels = [x for x in host.split(".") if x]
    suffix = labels[-1] if labels else ""
    return [
        math.log1p(len(url)), len(host), sum(1 for p in path.split("/") if p), sum(c.isdigit() for c in url) / max(1, len(url)), sum(c.isdigit() for c in host) / max(1, len(host)),
        _entropy(url), _entropy(host), len(params), math.log1p(max(map(len, params), default=0)), host.count("-"), len(labels), max(map(len, labels), default=0),
        url.count("%"), float("@" in host or ":" in host), float(bool(labels) and all(x.isdigit() for x in labels)), suffix_odds.get(suffix, 0.0), sum(word_odds.get(w, 0.0) for w in host_words(host)),
    ]


class BoostedTrees:
    """Binary gradient boosting: complete trees of fixed depth over feature quantiles."""

    def __init__(self, rounds: int = 30, depth: int = 3, rate: float = 0.3, bins: int = 32, least: float = 1.0):
        self.rounds, self.depth, self.rate, self.bins, self.least = rounds, depth, rate, bins, least

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins + 1)[1:-1])) for j in range(x.shape[1])]
        binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
        share = min(max(y.mean(), 1e-6), 1 - 1e-6) if len(y) else 0.5
        self.base, self.trees = math.log(share / (1 - share)), []
        score = np.full(len(y), self.base)
        for _ in range(self.rounds if len(y) else 0):
            p = 1 / (1 + np.exp(-score))
            grad, hess = p - y, p * (1 - p)
            node = np.zeros(len(y), dtype=np.int64)
            tree: list[tuple[int, float]] = []
            for level in range(self.depth):
                for k in range(2**level):
                    tree.append(self._split(binned, edges, grad, hess, np.flatnonzero(node == k)))
                here = tree[2**level - 1 :]
                feature, cut = np.array([f for f, _ in here]), np.array([c for _, c in here])
                node = 2 * node + (x[np.arange(len(y)), feature[node]] > cut[node])
            leaf = np.array([-self.rate * grad[node == k].sum() / (hess[node == k].sum() + self.least) for k in range(2**self.depth)])
            score = score + leaf[node]
            self.trees.append((np.array([f for f, _ in tree]), np.array([c for _, c in tree]), leaf))
        return self

    def _split(self, binned, edges, grad, hess, rows) -> tuple[int, float]:
        best, where = 1e-9, (0, math.inf)
        g, h = grad[rows].sum(), hess[rows].sum()
        for j, e in enumerate(edges):
            if not len(e):
                continue
            left_g = np.cumsum(np.bincount(binned[rows, j], grad[rows], len(e) + 1))[:-1]
            left_h = np.cumsum(np.bincount(binned[rows, j], hess[rows], len(e) + 1))[:-1]
            gain = left_g**2 / (left_h + self.least) + (g - left_g) ** 2 / (h - left_h + self.least) - g**2 / (h + self.least)
            k = int(np.argmax(gain))
            if gain[k] > best:
                best, where = gain[k], (j, float(e[k]))
        return where

    def probability(self, x: np.ndarray) -> np.ndarray:
        score = np.full(len(x), self.base)
        rows = np.arange(len(x))
        for feature, cut, leaf in self.trees:
            node = np.zeros(len(x), dtype=np.int64)
            for level in range(self.depth):
                at = node + 2**level - 1
                node = 2 * node + (x[rows, feature[at]] > cut[at])
            score += leaf[node]
        return 1 / (1 + np.exp(-score))


def _log_odds(seen: list[tuple], prior: float = 5.0, least: int = 12) -> dict[str, float]:
    """How much more often a key stands in unwanted URLs than in others, smoothed towards even.

    Keys seen less than ``least`` times have none: their odds would give away the label
    of the very URLs the trees are trained on.
    """
    total = [1 + sum(1 for _, bad in seen if bool(bad) == side) for side in (False, True)]
    counts: dict[str, list[int]] = {}
    for keys, bad in seen:
        for k in keys:
            counts.setdefault(k, [0, 0])[bool(bad)] += 1
    even = [prior * t / sum(total) for t in total]
    return {k: math.log((n[1] + even[1]) / (n[0] + even[0])) - math.log(total[1] / total[0]) for k, n in counts.items() if sum(n) >= least}


class UrlModel:
    """Statistics of suffixes and host words, and trees, fitted together on (url, unwanted) pairs."""

    def __init__(self, labelled: list[tuple[str | None, bool]]):
        labelled = labelled[:MAX_TRAINING]
        self.suffix_odds = _log_odds([([split_url(u)[0].rpartition(".")[2]], bad) for u, bad in labelled])
        self.word_odds = _log_odds([(set(host_words(split_url(u)[0])), bad) for u, bad in labelled])
        x = np.array([features(u, self.suffix_odds, self.word_odds) for u, _ in labelled], dtype=float).reshape(-1, len(FEATURES))
        self.trees = BoostedTrees().fit(x, np.array([float(b) for _, b in labelled]))

    def probability(self, urls: list[str | None]) -> np.ndarray:
        if not urls:
            return np.zeros(0)
        return self.trees.probability(np.array([features(u, self.suffix_odds, self.word_odds) for u in urls], dtype=float))


def labelled_urls(n: int = 3000, seed: int = 7) -> list[tuple[str, bool]]:
    """Labelled URLs made by rule: plain article addresses, and the lexical habits of spam
    (hyphenated bait words, random strings, address hosts, deep paths, many long parameters)."""
    rng = random.Random(seed)
    syllables = ["th", "er", "on", "an", "re", "in", "ti", "es", "ou", "sh", "nd", "ble", "ing", "tion", "de", "la", "que", "sch", "ver", "mar", "ko", "ne"]
    bait = "cheap spam free win pills casino bonus farm loans bet deal xxx hot money cash click seo replica ads track tracker adserver banner popup porn viagra poker lottery crypto adult sexy bets gambling discount warez".split()
    good_tlds, bad_tlds = ["com", "org", "net", "com", "org", "net", "edu", "de", "fr", "es", "info"], ["com", "net", "org", "com", "net", "org", "info", "biz", "top", "xyz", "click"]
    word = lambda a, b: "".join(rng.choice(syllables) for _ in range(rng.randint(a, b)))
    junk = lambda a, b: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz0123456789") for _ in range(rng.randint(a, b)))
    out: list[tuple[str, bool]] = []
    for i in range(n):
        scheme = rng.choice(["http", "https"])
        if i % 2:
            kind = rng.random()
            if kind < 0.55:
                host = "-".join(rng.sample(bait, rng.randint(2, 4))) + rng.choice(["", str(rng.randint(1, 99))])
            elif kind < 0.85:
                host = junk(12, 28)
            else:
                host = ".".join(str(rng.randint(1, 250)) for _ in range(4))
            if kind < 0.85:
                host = rng.choice(["", "www.", "blog.", "m.", "news.", junk(3, 8) + "."]) + host + rng.choice(["", ".example", ".example"]) + "." + rng.choice(bad_tlds)
            path = "/" + "/".join(rng.choice([junk(4, 16), rng.choice(["en", "de", "fr", "es"]), str(rng.randint(1, 999))]) for _ in range(rng.randint(0, 5)))
            if rng.random() < 0.4:
                path = f"/{rng.choice(['en', 'de', 'fr', 'es'])}/{rng.randint(1, 9999)}{rng.choice(['', '/', '.html'])}"
            query = rng.choice(["", "?page=2&ref=x", "?utm_source=feed"]) if rng.random() < 0.5 else "?" + "&".join(f"{junk(1, 6)}={junk(2, 24)}" for _ in range(rng.randint(1, 7)))
        else:
            host = rng.choice(["", "www.", "blog.", "m.", "news."]) + word(1, 4) + rng.choice(["", "", "", "-" + word(1, 2)]) + rng.choice(["", ".example", ".example"]) + "." + rng.choice(good_tlds)
            path = rng.choice(["", "/", f"/{rng.choice(['en', 'de', 'fr', 'es'])}/{rng.randint(1, 9999)}{rng.choice(['', '/', '.html'])}", "/" + "/".join(word(1, 4) for _ in range(rng.randint(1, 4))), f"/{rng.randint(2000, 2024)}/{rng.randint(1, 12):02d}/" + "-".join(word(1, 3) for _ in range(rng.randint(2, 6)))])
            query = rng.choice(["", "", "", "?page=2&ref=x", "?utm_source=feed", f"?id={rng.randint(1, 99999)}"])
        out.append((f"{scheme}://{host}{path}{query}{rng.choice(['', '', '', '#top'])}", bool(i % 2)))
    return out


@lru_cache(maxsize=1)
def default_model() -> UrlModel:
    return UrlModel([*labelled_urls(), ("", False), (None, False)])


@keeping
def judge_urls(pages: DataFrame, keep: tuple[str, ...] = ("page_id",), url: str = "url", rules: dict[str, str] | None = None, model: UrlModel | None = None, threshold: float = 0.5) -> DataFrame:
    """``keep``, host, path, rule, verdict and score (the trees' probability of unwanted).

    Null and malformed URLs have an empty host and path, fit no rule and are judged by the
    trees. Repeated rows are judged alike, URLs of any length whole; an empty table gives no rows.
    A kept column that has the name of a result comes back with ``_in`` added.
    """
    rules, model = RULES if rules is None else rules, model or default_model()
    fields = pages.select(*keep, url)
    schema = ", ".join(f"`{c}` {fields.schema[c].dataType.simpleString()}" for c in keep) + ", host string, path string, rule string, verdict string, score double"

    def judge(batches):
        for batch in batches:
            urls = batch.column(url).to_pylist()
            parts = [split_url(u) for u in urls]
            fits = [matching_rule(h, p, rules) for h, p in parts]
            score = model.probability(urls)
            verdict = [rules[f] if f is not None else "block" if s > threshold else "allow" for f, s in zip(fits, score, strict=True)]
            columns = [batch.column(c) for c in keep] + [pa.array([h for h, _ in parts], pa.string()), pa.array([p for _, p in parts], pa.string()), pa.array(fits, pa.string()), pa.array(verdict, pa.string()), pa.array(score, pa.float64())]
            yield pa.RecordBatch.from_arrays(columns, names=[*keep, "host", "path", "rule", "verdict", "score"])

    return fields.mapInArrow(judge, schema)


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Host, path, rule and verdict of every page's URL."""
    return judge_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict", F.round("score", 6).alias("score"))
