"""URL filter: host and path rules, and logistic regression on hashed character n-grams.

Rules (host, path) are column expressions: a rule fits its host and all
subdomains where the url's path starts with the rule's; the longest wins.  Urls
without a rule are judged by a logistic regression on hashed character n-grams of
host and path, trained from a small labelled URL table; scoring is one vectorised
pass over the bytes of a batch.

Defined results: a null url, or one without ``://``, has an empty host and path
and is allowed unless the model says otherwise for empty strings (it allows);
repeated rows repeat; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .textkernel import mix64

# The rules as (verdict, host, path).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
BITS, ORDERS = 16, (3, 4, 5)
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

# Words of unwanted and of ordinary hosts, from which the labelled table is made.
UNWANTED = (
    "cheap-pills", "free-bets", "casino-bonus", "online-casino", "poker-win", "hot-singles", "xxx-videos", "adult-cams", "porn-tube",
    "viagra-store", "pills-online", "payday-loans", "fast-cash", "replica-watches", "jackpot-slots", "bet-now", "escort-girls",
    "warez-download", "keygen-crack", "torrent-free", "win-prize", "lottery-winner", "crypto-doubler", "spam-offers", "weight-loss-pills",
    "free-money", "click-here-now", "sexy-chat", "nude-pics", "betting-tips",
)
ORDINARY = (
    "news", "weather", "library", "museum", "university", "research", "journal", "school", "science", "history", "recipes", "gardening",
    "travel", "music", "daily-times", "city-council", "health-service", "open-source", "docs", "encyclopedia", "bookshop", "theatre",
    "railway", "forum", "photography", "climate", "astronomy", "language-learning", "math-notes", "town-hall",
)


def labelled_urls(seed: int = 23) -> list[tuple[str, str, int]]:
    """A small table (host, path, 1 = unwanted), made by rule from the words above and neutral syllables."""
    rng = np.random.default_rng(seed)
    syllables = "the ion tion an er re th ing st en ti on es or ha nd ou ed at to is ble le ly ea de ment os ado che ver ung".split()
    tops = ["example.com", "example.org", "example.net", "test", "invalid.example"]
    subs = ["", "www.", "blog.", "m.", "shop."]
    paths = ["/", "/en/{n}", "/de/{n}/", "/fr/{n}.html", "/es/{n}", "/articles/{n}", "/{w}/{n}", ""]
    out = []
    out += [("", "", 0)] * 60  # what urls without a host come to
    for k in range(900):
        bad = k % 3 == 0
        neutral = "".join(rng.choice(syllables, int(rng.integers(2, 4))))
        name = str(rng.choice(UNWANTED)) if bad else (str(rng.choice(ORDINARY)) if k % 3 == 1 else neutral)
        if k % 5 == 0:
            name = f"{name}{rng.integers(1, 99)}" if k % 2 else f"{neutral}-{name}"
        host = f"{subs[k % len(subs)]}{name}.{tops[int(rng.integers(len(tops)))]}"
        path = paths[int(rng.integers(len(paths)))].format(n=rng.integers(1, 60_000), w=name if k % 2 else neutral)
        out.append((host, path, int(bad)))
    return out


def split_url(url: Column) -> tuple[Column, Column]:
    """(host, path) of a url."""
    url = F.coalesce(url, F.lit(""))
    mark = F.instr(url, "://")
    rest = F.when(mark > 0, F.substring(url, mark + 3, F.length(url))).otherwise(F.lit(""))
    raw = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(raw) + 1, F.length(rest)), r"^[^?#]*", 0)
    return F.translate(raw, UPPER, LOWER), path


def rule_name(rule: tuple[str, str, str]) -> str:
    return rule[1] + rule[2]


def matching_rule(host: Column, path: Column, rules: tuple[tuple[str, str, str], ...]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, else nulls."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(rule_name(r)), r)):  # the longest is asked first
        fits = ((host == rule[1]) | host.endswith("." + rule[1])) & path.startswith(rule[2])
        name, verdict = F.when(fits, F.lit(rule_name(rule))).otherwise(name), F.when(fits, F.lit(rule[0])).otherwise(verdict)
    return name, verdict


def gram_ids(texts: pa.Array, part: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature id) of every character n-gram of marked-up strings, repeats included."""
    mark = lambda sign: pa.scalar(sign, pa.large_string())
    texts = pc.binary_join_element_wise(mark("^"), texts.cast(pa.large_string()), mark("$"), mark(""))
    n = len(texts)
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + n + 1]
    raw = np.frombuffer(texts.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]].astype(np.uint64) if n else np.empty(0, np.uint64)
    offsets = offsets - offsets[0] if n else offsets
    owner = np.repeat(np.arange(n), np.diff(offsets)) if n else np.empty(0, np.int64)
    rows, ids = [], []
    for order in ORDERS:
        m = len(raw) - order + 1
        if m <= 0:
            continue
        code = np.full(m, np.uint64(order * 1000 + part), dtype=np.uint64)
        for k in range(order):
            code = code * np.uint64(1_000_003) + raw[k : k + m]
        inside = owner[:m] == owner[order - 1 : order - 1 + m]
        rows.append(owner[:m][inside])
        ids.append((mix64(code[inside]) >> np.uint64(64 - BITS)).astype(np.int64))
    none = np.empty(0, dtype=np.int64)
    return (np.concatenate(rows), np.concatenate(ids)) if rows else (none, none)


def _design(hosts: pa.Array, paths: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    parts = [gram_ids(column, part) for part, column in enumerate((hosts, paths))]
    rows, ids = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    return rows, ids, 1 / np.sqrt(np.maximum(np.bincount(rows, minlength=len(hosts)), 1))


def fit(table: list[tuple[str, str, int]], steps: int = 400, rate: float = 4.0, ridge: float = 1e-4) -> tuple[np.ndarray, float]:
    """Weights and bias by full-batch gradient descent with momentum."""
    rows, ids, norm = _design(pa.array([t[0] for t in table], pa.large_string()), pa.array([t[1] for t in table], pa.large_string()))
    y = np.array([t[2] for t in table], dtype=float)
    w, bias, speed, pace = np.zeros(1 << BITS), 0.0, np.zeros(1 << BITS), 0.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(rows, w[ids], len(y)) * norm + bias, -30, 30)))
        g = (p - y) / len(y)
        speed = 0.9 * speed - rate * (np.bincount(ids, (g * norm)[rows], 1 << BITS) + ridge * w)
        pace = 0.9 * pace - rate * 0.1 * g.sum()
        w, bias = w + speed, bias + pace
    return w, float(bias)


def judge(pages: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES, table: list[tuple[str, str, int]] | None = None, threshold: float = 0.5) -> DataFrame:
    """(page_id, host, path, rule, verdict, score) of every page."""
    weights, bias = fit(labelled_urls() if table is None else table)
    shared = pages.sparkSession.sparkContext.broadcast((weights.astype(np.float32), bias))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, b = shared.value
        for batch in batches:
            rows, ids, norm = _design(batch.column("host"), batch.column("path"))
            score = 1 / (1 + np.exp(-np.clip(np.bincount(rows, w[ids], len(batch)) * norm + b, -30, 30)))
            named = ["block" if s >= threshold else "allow" for s in score]
            verdict = pc.coalesce(batch.column("verdict"), pa.array(named, batch.schema.field("verdict").type))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("page_id", "host", "path", "rule")), verdict, pa.array(score, pa.float64())], ["page_id", "host", "path", "rule", "verdict", "score"])

    host, path = split_url(F.col("url").cast("string"))
    split = pages.select("page_id", host.alias("host"), path.alias("path"))
    rule, verdict = matching_rule(F.col("host"), F.col("path"), rules)
    kind = dict(pages.dtypes)["page_id"]
    return split.select("page_id", "host", "path", rule.alias("rule"), verdict.alias("verdict")).mapInArrow(run, f"page_id {kind}, host string, path string, rule string, verdict string, score double")
