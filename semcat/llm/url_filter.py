"""URL filters: host and path rules first, then logistic regression on hashed character n-grams of host and path.

The labelled URL table is small and made here, as no table of labelled URLs is given: its labels come from a list of words for
unwanted and wanted subjects, put into URLs of six shapes by templates. The model generalises such a list to parts of words
and to new combinations; it knows nothing about subjects that the list does not name.
"""

from __future__ import annotations

import random
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_batches, mix, span_hashes

#: Fixed values: (action, host, path) of the rules.
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)

BITS = 14
_DIGITS = re.compile("[0-9]+")
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: The small labelled URL table is made of these words: subjects and trimmings of unwanted sites, subjects of wanted ones.
#: No host was copied from a table; made-up names stand for hosts whose name says nothing.
UNWANTED = "casino poker slots roulette jackpot bets betting lottery pills viagra pharmacy loans payday replica adult escort porn xxx warez keygen cracked torrent spam clicks prizes giveaway doubler singles ads adserver advertising banner popup tracker track tracking pixel beacon telemetry affiliate linkfarm backlinks".split()
TRIMMINGS = "win free cheap online best bonus club hub zone store deals now".split()
WANTED = "news library university museum recipes weather gardening history physics travel health council school journal encyclopedia football cinema orchestra hospital railway biology theatre parliament harbour bakery village forest mountain river bridge painting literature grammar dictionary atlas observer chronicle gazette review".split()


def labelled_urls(made_up: int = 240, seed: int = 7) -> list[tuple[str, str, int]]:
    """(host, path, unwanted) of the training table: each name in six URL shapes, the same for both labels. A subject stands
    alone, with a trimming or with a made-up name; made-up names alone and with wanted subjects are wanted, so that the
    subject decides and not what stands beside it."""
    shapes = [("{}.example.com", "/en/{}"), ("www.{}.example.org", "/de/{}.html"), ("m.{}.example.net", "/fr/{}/"), ("blog.{}.example.com", "/es/{}"), ("{}.org", "/page/{}"), ("www.{}.net", "/{}/index.html")]
    rng = random.Random(seed)
    syllable = lambda: rng.choice("bcdfghjklmnprstvwz") + rng.choice("aeiou") + rng.choice(("", "n", "r", "s", "t"))
    name = lambda: "".join(syllable() for _ in range(rng.randint(1, 3)))
    trim = lambda i: TRIMMINGS[i % len(TRIMMINGS)]
    bad = [x for i, w in enumerate(UNWANTED) for x in (w, f"{w}-{trim(i)}", f"{trim(i + 5)}-{w}", f"{w}{trim(i + 7)}", f"{w}-{name()}", f"{name()}-{w}")]
    good = [x for i, w in enumerate(WANTED) for x in (w, f"{w}-{WANTED[(i + 9) % len(WANTED)]}", f"{w}-{name()}", f"{name()}-{w}", f"{trim(i)}-{w}")] + [x for _ in range(made_up) for x in (name() + syllable(), f"{name()}-{name()}")]
    return [(h.format(w), p.format(137 * i + 11 * k), y) for y, words in ((1, bad), (0, good)) for i, w in enumerate(words) for k, (h, p) in enumerate(shapes)]


def split_url(url: Column) -> tuple[Column, Column]:
    """(host, path): host after the first :// up to / ? # or the end, A-Z lower-cased; path then up to ? # or the end."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + F.lit(3), F.length(url))).otherwise("")
    host = F.regexp_extract(rest, r"(?s)\A([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"(?s)\A[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, _UPPER, _LOWER), F.lit("")), F.coalesce(path, F.lit(""))


def best_rule(host: Column, path: Column, rules=RULES) -> Column:
    """The longest fitting rule as struct(rule, verdict), or null. A rule fits its host and all subdomains."""
    out = F.lit(None)
    for action, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(action).alias("verdict"))).otherwise(out)
    return out


def _buffer(parts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of the parts, each between ^ and $."""
    raw = [f"^{x or ''}$".encode() for x in parts]
    return np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)])


def ngram_slots(hosts: list[str | None], paths: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(row, slot): the distinct hash slots of the 3- to 5-grams of bytes of each host and path, told apart by a mark of the
    part; runs of digits of a path count as one 0. All rows of a batch are hashed at once."""
    found = []
    for mark, parts in ((1, hosts), (2, [_DIGITS.sub("0", x or "") for x in paths])):
        data, offsets = _buffer(parts)
        for n in (3, 4, 5):
            at = np.arange(max(0, len(data) - n + 1))
            row = np.searchsorted(offsets, at, "right") - 1
            at, row = (x[at + n <= offsets[row + 1]] for x in (at, row))
            h = mix(span_hashes(data, at, at + n) + np.uint64(mark))
            found.append(row << BITS | (h & np.uint64((1 << BITS) - 1)).astype(np.int64))
    pairs = np.unique(np.concatenate(found))
    return pairs >> BITS, pairs & ((1 << BITS) - 1)


@lru_cache
def fit(epochs: int = 600, rate: float = 0.3, decay: float = 1e-4) -> tuple[np.ndarray, float]:
    """Weights and intercept by full-batch gradient descent with momentum; deterministic."""
    rows = labelled_urls()
    row, col = ngram_slots([h for h, _, _ in rows], [p for _, p, _ in rows])
    y = np.array([r[2] for r in rows], float)
    scale = 1 / np.sqrt(np.bincount(row))
    w, b, v, vb = np.zeros(1 << BITS), 0.0, np.zeros(1 << BITS), 0.0
    for _ in range(epochs):
        p = 1 / (1 + np.exp(-(np.bincount(row, w[col]) * scale + b)))
        g = (p - y) / len(y)
        v = 0.9 * v + np.bincount(col, (g * scale)[row], 1 << BITS) * 10 + decay * w
        vb = 0.9 * vb + g.sum()
        w, b = w - rate * v, b - rate * vb
    return w, float(b)


def probabilities(hosts: list[str | None], paths: list[str | None], w: np.ndarray, b: float) -> np.ndarray:
    """Probability that each URL is unwanted; 0 without a host, as nothing then speaks against it."""
    row, slot = ngram_slots(hosts, paths)
    n = np.bincount(row, minlength=len(hosts))
    z = np.bincount(row, w[slot], len(hosts)) / np.sqrt(np.maximum(n, 1)) + b
    return np.where([bool(h) for h in hosts], 1 / (1 + np.exp(-z)), 0.0)


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", threshold: float = 0.5) -> DataFrame:
    """(id, host, path, rule, verdict, score) for every row. verdict: the rule's, else block where the model's probability is
    at least ``threshold``. A null url, one without ://, or one whose host is empty fits no rule unless its path does, scores 0 and
    is allowed. A long url is judged whole. Repeated rows give repeated results; an empty input gives none; other columns are
    ignored."""
    w, b = fit()
    host, path = split_url(F.col(url_col).cast("string"))
    rows = pages.select(F.col(id_col).alias("id_"), host.alias("host"), path.alias("path"))

    def rate(t: pa.RecordBatch) -> pa.RecordBatch:
        hosts, paths = t.column("host").to_pylist(), t.column("path").to_pylist()
        s = [probabilities(hosts[k : k + 1024], paths[k : k + 1024], w, b) for k in range(0, len(hosts), 1024)]
        return pa.RecordBatch.from_arrays([*t.columns, pa.array(np.concatenate(s), pa.float64())], [*t.schema.names, "score"])

    kind = rows.schema["id_"].dataType.simpleString()
    scored = map_batches(rows, rate, f"id_ {kind}, host string, path string, score double")
    best = best_rule(F.col("host"), F.col("path"))
    out = scored.withColumn("best", best)
    return out.select(F.col("id_").alias(id_col), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.when(F.col("score") >= threshold, "block").otherwise("allow")).alias("verdict"), "score")
