"""URL filters: rules of host and path first, then gradient-boosted trees on lexical features.

A rule names a host and a path prefix; it fits that host and its subdomains, and the longest fitting rule decides. URLs
that a rule decides are the labelled ones: a bounded sample of distinct ones trains the trees, which decide the rest. Hosts, paths
and rules are JVM expressions; tree scores come in Arrow batches.

Features: lengths of url, host, path and query, depth of path and of host, shares of digits, letters and other
signs, character entropy, number of parameters, length of the longest label, and statistics of the host's last label,
of its last two, and of the path's first part (how often they are blocked among labelled urls, smoothed, and how frequent they are). A training url's own
suffix statistics come from the four fifths of the sample that it is not in, so that no label explains itself.

Edge cases: a url that is null or lacks ``://`` has empty host and path and no rule; without labelled urls of both kinds
the trees give that one kind's verdict (allow without any); ties of rule length go to the rule named first; repeated rows
get the same verdict, and a url counts once in training however often it occurs; a url of any length is read whole; an empty
table gives no rows; other columns are kept unless they bear a result's name.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dpgrid.llm.arrow import column, out, strings
from dpgrid.llm.sampling import least_hashed

#: Distinct labelled urls that are learnt from, at most; parts of the sample for suffix statistics.
SAMPLE, FOLDS = 20_000, 5
#: Trees, their depth, shrinkage, bins per feature, least rows in a leaf.
TREES, DEPTH, RATE, BINS, LEAST = 60, 4, 0.15, 32, 5
_CHUNK = 4096


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def text(self) -> str:
        return self.host + self.path


def _ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty for null or without ``://``."""
    at = F.locate("://", url)
    rest = F.substring(url, at + 3, F.length(url))
    host = F.when(at > 0, _ascii_lower(F.regexp_extract(rest, r"^([^/?#]*)", 1))).otherwise("")
    path = F.when(at > 0, F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)).otherwise("")
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def rule_of(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """Text and verdict of the longest fitting rule, else nulls: one CASE, longest rules first."""
    text = verdict = None
    for r in sorted(rules, key=lambda r: -len(r.text)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        text = F.when(fits, r.text) if text is None else text.when(fits, r.text)
        verdict = F.when(fits, r.verdict) if verdict is None else verdict.when(fits, r.verdict)
    null = F.lit(None).cast("string")
    return (null, null) if text is None else (text, verdict)


NAMES = ("url_length", "host_length", "path_length", "query_length", "depth", "labels", "digits", "letters", "signs", "entropy", "parameters", "longest_label", "tld_blocked", "tld_count", "domain_blocked", "domain_count", "lead_blocked", "lead_count")


def parts_of(host: str, path: str) -> tuple[str, str, str]:
    """Names under which the last label, the last two, and the first part of the path are counted."""
    labels = host.split(".")
    return labels[-1], "." + ".".join(labels[-2:]), "/" + path[1:].partition("/")[0]


def lexical(urls: list[str | None], hosts: list[str], paths: list[str], stats: dict[str, tuple[float, float]], base: float) -> np.ndarray:
    """Feature rows in the order of ``NAMES``."""
    made = np.zeros((len(urls), len(NAMES)))
    for i, (url, host, path) in enumerate(zip(urls, hosts, paths, strict=True)):
        u = (url or "").encode("utf-8", "replace")
        byte = np.frombuffer(u, np.uint8)
        seen = np.bincount(byte, minlength=128)
        share = seen[seen > 0] / max(1, len(u))
        digits = int(seen[48:58].sum())
        letters = int(seen[65:91].sum() + seen[97:123].sum())
        query = u.partition(b"#")[0].partition(b"?")[2]
        known = [x for name in parts_of(host, path) for x in stats.get(name, (base, 0.0))]
        size = max(1, len(u))
        made[i] = (
            len(u), len(host), len(path), len(query), path.count("/"), host.count(".") + 1, digits / size, letters / size, (len(u) - digits - letters) / size,
            -(share * np.log2(share)).sum(), len([p for p in query.split(b"&") if p]), max(map(len, host.split("."))), *known,
        )
    return made


def suffix_stats(hosts: list[str], paths: list[str], y: np.ndarray, smooth: float = 4.0, grow: float = 1.0) -> tuple[dict[str, tuple[float, float]], float]:
    """Smoothed blocked share and log count of every name of ``parts_of``; ``grow`` scales the counts of a part to the whole."""
    base = float(y.mean()) if len(y) else 0.0
    seen: dict[str, list[float]] = {}
    for host, path, label in zip(hosts, paths, y, strict=True):
        for key in parts_of(host, path):
            pair = seen.setdefault(key, [0.0, 0.0])
            pair[0] += label
            pair[1] += 1
    return {k: ((s + smooth * base) / (n + smooth), float(np.log1p(grow * n))) for k, (s, n) in seen.items()}, base


@dataclass
class Boosted:
    """Trees of full depth as arrays: split feature, split value and leaf value by heap position."""

    features: np.ndarray
    cuts: np.ndarray
    leaves: np.ndarray
    start: float

    def __call__(self, x: np.ndarray) -> np.ndarray:
        """Log odds of block."""
        z = np.full(len(x), self.start)
        rows = np.arange(len(x))
        for f, c, leaf in zip(self.features, self.cuts, self.leaves, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(DEPTH):
                at = 2 * at + 1 + (x[rows, f[at]] > c[at])
            z += leaf[at - (2**DEPTH - 1)]
        return z


def boost(x: np.ndarray, y: np.ndarray, l2: float = 1.0) -> Boosted:
    """Newton boosting of the logistic loss over quantile bins."""
    none = Boosted(np.zeros((0, 2**DEPTH - 1), np.int64), np.zeros((0, 2**DEPTH - 1)), np.zeros((0, 2**DEPTH)), -50.0)
    if not len(y) or y.min() == y.max():
        none.start = 50.0 if len(y) and y[0] else -50.0
        return none
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS + 1)[1:-1])) for j in range(x.shape[1])]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], 1)
    start = float(np.log(y.mean() / (1 - y.mean())))
    z = np.full(len(y), start)
    all_f, all_c, all_l = [], [], []
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-z))
        g, h = p - y, p * (1 - p)
        f, c, leaf = np.zeros(2**DEPTH - 1, np.int64), np.full(2**DEPTH - 1, np.inf), np.zeros(2**DEPTH)
        at = np.zeros(len(y), np.int64)
        for level in range(DEPTH):
            first, nodes = 2**level - 1, 2**level
            local = at - first
            best = np.full(nodes, 1e-9)
            for j, e in enumerate(edges):
                if not len(e):
                    continue
                width = len(e) + 1
                place = local * width + binned[:, j]
                sums = [np.bincount(place, w, nodes * width).reshape(nodes, width).cumsum(1) for w in (g, h, np.ones_like(g))]
                gl, hl, nl = (s[:, :-1] for s in sums)
                gt, ht, nt = (s[:, -1:] for s in sums)
                gain = gl**2 / (hl + l2) + (gt - gl) ** 2 / (ht - hl + l2) - gt**2 / (ht + l2)
                gain[(nl < LEAST) | (nt - nl < LEAST)] = -1
                k = gain.argmax(1)
                won = gain[np.arange(nodes), k] > best
                best[won] = gain[np.arange(nodes), k][won]
                f[first : first + nodes][won], c[first : first + nodes][won] = j, e[k[won]]
            at = 2 * at + 1 + (x[np.arange(len(y)), f[at]] > c[at])
        at -= 2**DEPTH - 1
        leaf = -RATE * np.bincount(at, g, 2**DEPTH) / (np.bincount(at, h, 2**DEPTH) + l2)
        z += leaf[at]
        all_f.append(f)
        all_c.append(c)
        all_l.append(leaf)
    return Boosted(np.array(all_f), np.array(all_c), np.array(all_l), start)


@dataclass
class UrlModel:
    trees: Boosted
    stats: dict[str, tuple[float, float]]
    base: float

    def blocked(self, urls: list[str | None], hosts: list[str], paths: list[str]) -> np.ndarray:
        """Probability of block."""
        z = self.trees(lexical(urls, hosts, paths, self.stats, self.base))
        return 1 / (1 + np.exp(-np.clip(z, -50, 50)))


def fit_urls(urls: list[str | None], hosts: list[str], paths: list[str], y: np.ndarray) -> UrlModel:
    """Trees on features whose suffix statistics leave out the url's own fold; scoring uses those of all urls."""
    stats, base = suffix_stats(hosts, paths, y)
    x, fold = np.zeros((len(urls), len(NAMES))), np.arange(len(urls)) % FOLDS
    for f in range(FOLDS if len(urls) >= FOLDS else 0):
        own, rest = np.flatnonzero(fold == f), np.flatnonzero(fold != f)
        others = suffix_stats([hosts[i] for i in rest], [paths[i] for i in rest], y[rest], grow=FOLDS / (FOLDS - 1))
        x[own] = lexical([urls[i] for i in own], [hosts[i] for i in own], [paths[i] for i in own], *others)
    return UrlModel(boost(x, y), stats, base)


def held_out_error(urls: list[str | None], hosts: list[str], paths: list[str], y: np.ndarray) -> float:
    """Share of wrong verdicts on the last fifth of the urls, of trees that learnt from the rest."""
    n = len(urls) * 4 // 5
    p = fit_urls(urls[:n], hosts[:n], paths[:n], y[:n]).blocked(urls[n:], hosts[n:], paths[n:])
    return float(((p >= 0.5) != (y[n:] > 0)).mean())


def with_rules(pages: DataFrame, rules: list[Rule], url_col: str = "url") -> DataFrame:
    """``pages`` with host, path, rule and the rule's verdict (null where no rule fits)."""
    host, path = host_and_path(F.col(url_col))
    split = pages.drop("host", "path", "rule", "verdict", "blocked").withColumns({"host": host, "path": path})
    text, verdict = rule_of(F.col("host"), F.col("path"), rules)
    return split.withColumns({"rule": text, "verdict": verdict})


def labelled(ruled: DataFrame, url_col: str = "url", sample: int = SAMPLE) -> tuple[list[str | None], list[str], list[str], np.ndarray]:
    """Urls, hosts, paths and verdicts (1: block) of at most ``sample`` distinct urls that a rule decides: those of least hash."""
    chosen = ruled.where(F.col("verdict").isNotNull()).select(F.col(url_col).alias("url"), "host", "path", (F.col("verdict") == "block").cast("double").alias("y"))
    got = least_hashed(chosen, ["url", "host", "path", "y"], sample).toArrow()
    return got["url"].to_pylist(), got["host"].to_pylist(), got["path"].to_pylist(), got["y"].to_numpy()


def train(ruled: DataFrame, url_col: str = "url", sample: int = SAMPLE) -> UrlModel:
    """Fit on a bounded sample of the urls that a rule decides."""
    return fit_urls(*labelled(ruled, url_col, sample))


def judge(pages: DataFrame, rules: list[Rule], url_col: str = "url", sample: int = SAMPLE) -> DataFrame:
    """``pages`` with host, path, rule, verdict, and the trees' probability ``blocked`` of every url."""
    ruled = with_rules(pages, rules, url_col)
    model = train(ruled, url_col, sample)
    schema = T.StructType([*ruled.schema.fields, T.StructField("blocked", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, _CHUNK):
                piece = whole.slice(i, _CHUNK)
                p = model.blocked(strings(piece, url_col), strings(piece, "host"), strings(piece, "path"))
                verdict = pa.array([v or ("block" if q >= 0.5 else "allow") for v, q in zip(strings(piece, "verdict"), p, strict=True)], pa.string())
                cols = {n: column(piece, n) for n in piece.schema.names} | {"verdict": verdict, "blocked": pa.array(p)}
                yield out([*cols], *cols.values())

    return ruled.mapInArrow(run, schema)
