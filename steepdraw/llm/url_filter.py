"""URL verdicts: suffix rules first, gradient-boosted trees on lexical features for the rest.

The trees are fitted on URLs that carry a label; in the driver query these are the URLs that a
rule decides (allow or block).  At most `train_rows` labelled URLs are used, those with the
smallest hashes, so the choice depends on the rows alone and not on how they are partitioned.
Features: lengths, depth, digit ratio, character entropy, parameter counts, and the smoothed
block rates of the host's suffixes and of the first path segment among the training rows.
Scoring is one narrow Arrow pass over all rows.  Null and malformed URLs have empty host and
path.  With labels of one kind, or none, every URL without a rule gets `default`.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed values of the driver's contract: (host, path prefix, verdict).
RULES = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))
TRAIN_ROWS = 20_000
BINS = 32


def with_host_path(pages: DataFrame) -> DataFrame:
    """Adds host (A-Z lowered) and path by plain string search; both empty without `://`."""
    at = F.instr("url", "://")
    rest = F.when(at > 0, F.substring("url", at + F.lit(3), F.length("url"))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return pages.withColumns({"host": host, "path": F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)})


def with_rule(hosts: DataFrame, rules: tuple = RULES) -> DataFrame:
    """Adds rule and rule_verdict of the longest fitting rule (null if none)."""
    hit = F.lit(None).cast("string")
    verdict = F.lit(None).cast("string")
    for host, prefix, v in sorted(rules, key=lambda r: len(r[0] + r[1])):  # later ones win
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(prefix)
        hit = F.when(fits, F.lit(host + prefix)).otherwise(hit)
        verdict = F.when(fits, F.lit(v)).otherwise(verdict)
    return hosts.withColumns({"rule": hit, "rule_verdict": verdict})


def suffixes(host: str) -> list[str]:
    """The last one and two labels of a host: where registries and owners show."""
    labels = host.split(".")
    return [".".join(labels[-k:]) for k in (1, 2)]


def _entropy(text: str) -> float:
    n = len(text)
    return -sum(c / n * math.log2(c / n) for c in Counter(text).values()) if n else 0.0


def lexical(url: str | None, host: str, path: str) -> list[float]:
    url = url or ""
    query = url.partition("?")[2].partition("#")[0]
    digits = sum(c.isdigit() for c in url)
    parts = [p for p in path.split("/") if p]
    return [
        len(url), len(host), len(path), len(parts), host.count("."), host.count("-"), digits / max(1, len(url)), sum(c.isdigit() for c in host),
        _entropy(url), _entropy(host), query.count("=") if query else 0, len(query), url.count("#"), url.count("%"), float(url.startswith("https")), max((len(p) for p in parts), default=0),
    ]


class UrlModel:
    """Boosted regression trees on logistic loss, over binned features."""

    def __init__(self, rounds: int = 60, depth: int = 3, rate: float = 0.2, least: int = 20, ridge: float = 1.0) -> None:
        self.rounds, self.depth, self.rate, self.least, self.ridge = rounds, depth, rate, least, ridge
        self.trees: list[tuple] = []

    def features(self, rows: list[tuple]) -> np.ndarray:
        out = []
        for url, host, path in rows:
            tags = [*suffixes(host), "/" + path.strip("/").partition("/")[0]]
            out.append([*lexical(url, host, path), *(self.rates.get((i, t), self.prior) for i, t in enumerate(tags))])
        return np.array(out, dtype=np.float64).reshape(len(rows), -1)

    def fit(self, rows: list[tuple], blocked: np.ndarray) -> UrlModel:
        self.prior = float(blocked.mean())
        seen: dict = defaultdict(lambda: [0.0, 0.0])
        for (_, host, path), y in zip(rows, blocked.tolist(), strict=True):
            for i, t in enumerate([*suffixes(host), "/" + path.strip("/").partition("/")[0]]):
                seen[i, t][0] += y
                seen[i, t][1] += 1
        self.rates = {k: (a + 10 * self.prior) / (b + 10) for k, (a, b) in seen.items()}
        x = self.features(rows)
        self.cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS + 1)[1:-1])) for j in range(x.shape[1])]
        binned = self._binned(x)
        self.base = math.log(max(self.prior, 1e-6) / max(1 - self.prior, 1e-6))
        score = np.full(len(rows), self.base)
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-score))
            tree = self._grow(binned, blocked - p, p * (1 - p), np.arange(len(rows)), self.depth)
            self.trees.append(tree)
            score += self._apply(tree, binned)
        return self

    def _binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(self.cuts)], axis=1).astype(np.uint8)

    def _grow(self, binned: np.ndarray, grad: np.ndarray, hess: np.ndarray, own: np.ndarray, depth: int) -> tuple:
        g, h = grad[own].sum(), hess[own].sum()
        best = (1e-6, -1, -1)
        if depth and len(own) >= 2 * self.least:
            for j in range(binned.shape[1]):
                b = binned[own, j]
                gs, hs, ns = (np.cumsum(np.bincount(b, w, minlength=BINS))[:-1] for w in (grad[own], hess[own], None))
                gain = gs**2 / (hs + self.ridge) + (g - gs) ** 2 / (h - hs + self.ridge) - g**2 / (h + self.ridge)
                gain[(ns < self.least) | (len(own) - ns < self.least)] = -1
                k = int(np.argmax(gain))
                best = max(best, (float(gain[k]), -j, k), key=lambda t: (t[0], t[1])) if gain[k] > best[0] else best
        if best[2] < 0:
            return (self.rate * g / (h + self.ridge),)
        j, k = -best[1], best[2]
        left = binned[own, j] <= k
        return (j, k, self._grow(binned, grad, hess, own[left], depth - 1), self._grow(binned, grad, hess, own[~left], depth - 1))

    def _apply(self, tree: tuple, binned: np.ndarray) -> np.ndarray:
        if len(tree) == 1:
            return np.full(len(binned), tree[0])
        j, k, low, high = tree
        return np.where(binned[:, j] <= k, self._apply(low, binned), self._apply(high, binned))

    def probability(self, rows: list[tuple]) -> np.ndarray:
        binned = self._binned(self.features(rows))
        score = np.full(len(rows), self.base)
        for tree in self.trees:
            score += self._apply(tree, binned)
        return 1 / (1 + np.exp(-score))


def fit_model(labelled: DataFrame, train_rows: int = TRAIN_ROWS) -> UrlModel | None:
    """Model from (url, host, path, blocked); None if the labels are all of one kind.

    Trains on the train_rows distinct URLs with the least hashes.  A bound on the hash, from the
    number of distinct URLs, leaves little more than those to sort, so tasks send few rows.
    """
    hashed = labelled.select("url", "host", "path", "blocked", F.xxhash64("url").alias("hash"))
    n = hashed.agg(F.approx_count_distinct("hash", 0.02).alias("n")).first()["n"]
    share = 1.2 * train_rows / max(1, n)
    few = hashed if share >= 1 else hashed.where(F.col("hash") <= int(share * 2**64) - 2**63)
    rows = few.dropDuplicates(["url"]).orderBy("hash", "url").limit(train_rows).collect()
    blocked = np.array([float(r.blocked) for r in rows])
    if not len(rows) or blocked.min() == blocked.max():
        return None
    return UrlModel().fit([(r.url, r.host, r.path) for r in rows], blocked)


def judge(pages: DataFrame, rules: tuple = RULES, train_rows: int = TRAIN_ROWS, default: str = "allow") -> DataFrame:
    """page_id, url, host, path, rule, verdict, block_probability."""
    ruled = with_rule(with_host_path(pages.select("page_id", F.col("url").cast("string").alias("url"))), rules)
    model = fit_model(ruled.where("rule_verdict is not null and url is not null").withColumn("blocked", F.col("rule_verdict") == "block"), train_rows)
    sent = pages.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            url, host, path, own = (b.column(i).to_pylist() for i in (1, 2, 3, 5))
            if sent.value is None:
                p = [None] * len(url)
                verdict = [o or default for o in own]
            else:
                p = sent.value.probability(list(zip(url, host, path, strict=True))).tolist() if url else []
                verdict = [o or ("block" if q > 0.5 else "allow") for o, q in zip(own, p, strict=True)]
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(5)), pa.array(verdict, pa.string()), pa.array(p, pa.float64())], names=["page_id", "url", "host", "path", "rule", "verdict", "block_probability"])

    return ruled.mapInArrow(run, f"page_id {dict(pages.dtypes)['page_id']}, url string, host string, path string, rule string, verdict string, block_probability double")
