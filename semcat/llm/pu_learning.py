"""Positive-unlabelled text classifiers in numpy: toxicity and quality.

Both learn from trusted positives and unlabelled text by the non-negative risk estimator: the risk of the negatives is taken
from the unlabelled texts less the class prior times the positives' share, and held at zero or more. Texts are described by
the presence of hashed tokens (runs of letters and digits, runs of other signs), for toxicity also of the tokens' first bytes,
so that varied forms of a word share a feature, and by a few proportions.
"""

from __future__ import annotations

from dataclasses import dataclass
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, blocks, fold, map_batches, span_hashes, utf8, word_spans

#: Classes of bytes: 0 white space, 1 letters, digits and all bytes beyond ASCII, 2 other signs.
_CLASS = np.full(256, 2, np.uint8)
_CLASS[:33] = 0
_CLASS[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = 1
DENSE = 6
_SLOTS = 1 << 20
_PREFIX = np.uint64(0x5BD1E9955BD1E995)
#: How the features of toxicity are picked (chosen on an inner split of the learning folds): its marks are rare and vary in form.
TOXIC_FEATURES = {"prefix": 5, "min_z": 3.0, "floor": 3, "features": 16384}


def tokens(col: pa.Array, prefix: int = 0):
    """For runs of documents: (first row, rows, token hashes, document of each token, proportions of each document). With
    ``prefix``, the hash of the first so many bytes follows each token's own."""
    data, offsets, _ = utf8(col)
    for i, j in blocks(offsets):
        off = offsets[i : j + 1] - offsets[i]
        raw = data[offsets[i] : offsets[j]]
        starts, ends, doc = word_spans(raw, off, _CLASS)
        h = span_hashes(LOWER[raw], starts, ends)
        rows = j - i
        word = _CLASS[raw[starts]] == 1 if len(starts) else np.zeros(0, bool)
        n = np.bincount(doc, minlength=rows).astype(float)
        words = np.bincount(doc, word, rows)
        size = np.bincount(doc, (ends - starts) * word, rows)
        bounds = np.r_[0, np.cumsum((raw >= 65) & (raw <= 90))]
        upper = (bounds[off[1:]] - bounds[off[:-1]]).astype(float)
        some = np.maximum(n, 1)
        dense = np.column_stack([(n - words) / some, size / np.maximum(words, 1) / 10, upper / np.maximum(size, 1), np.log1p(n) / 10, n == 0, np.ones(rows)])
        if prefix:
            h = np.column_stack([h, span_hashes(LOWER[raw], starts, np.minimum(ends, starts + prefix)) ^ _PREFIX]).ravel()
            doc = np.repeat(doc, 2)
        yield i, rows, h, doc, dense


@dataclass
class PuModel:
    """Token hashes (sorted) with weights, and the weights of the proportions."""

    hashes: np.ndarray
    weights: np.ndarray
    dense: np.ndarray
    prior: float
    prefix: int = 0


def _sample(documents: DataFrame, ids: DataFrame, id_col: str, text_col: str, prefix: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """(distinct token hashes, proportions) of the documents with these ids; ``ids`` has a bounded number of different ids. An
    id counts once, with its least text where rows repeat it, so the rows that reach the driver are bounded too."""
    picked = documents.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(ids), "id", "left_semi")
    picked = picked.groupBy("id").agg(F.min("text").alias("text")).select("text")

    def describe(b: pa.RecordBatch) -> pa.RecordBatch:
        hs, ds = [], []
        for _, rows, h, doc, dense in tokens(b.column(0), prefix):
            first = np.searchsorted(doc, np.arange(rows + 1))
            for d in range(rows):
                hs.append(np.unique(h[first[d] : first[d + 1]]).view(np.int64))
                ds.append(dense[d])
        return pa.RecordBatch.from_arrays([pa.array(hs, pa.list_(pa.int64())), pa.array(ds, pa.list_(pa.float64()))], ["h", "d"])

    got = map_batches(picked, describe, "h array<long>, d array<double>").toArrow()
    # views of the chunks as they came: no second copy of the hashes on the driver, and a short digest in the sort
    hashes = [x.values.to_numpy().view(np.uint64) for chunk in got.column("h").chunks for x in chunk]
    dense = np.array(got.column("d").to_pylist(), float).reshape(len(hashes), DENSE)
    order = sorted(range(len(hashes)), key=lambda i: (tuple(dense[i]), blake2b(hashes[i], digest_size=16).digest()))
    return [(hashes[i], dense[i]) for i in order]


def _counts(rows: list[tuple[np.ndarray, np.ndarray]], most: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes, and how many rows hold each; hashes are joined and merged in runs of about ``most``."""
    values, counts = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    i = 0
    while i < len(rows):
        j, size = i, 0
        while j < len(rows) and size < most:
            size, j = size + len(rows[j][0]), j + 1
        v, c = np.unique(np.concatenate([h for h, _ in rows[i:j]]), return_counts=True)
        both = np.union1d(values, v)
        total = np.zeros(len(both), np.int64)
        total[np.searchsorted(both, values)] = counts
        total[np.searchsorted(both, v)] += c
        values, counts, i = both, total, j
    return values, counts


def non_negative_fit(x_pos, x_unl, width: int, dense_pos, dense_unl, prior: float, epochs: int = 1500, rate: float = 0.05, decay: float = 0.015, slack: float = 0.0):
    """Weights of a logistic model under the non-negative risk. x_*: (row, feature) index pairs of binary features.
    The weight of the squared-norm penalty is ``decay`` divided by the number of positives, as for a fixed Gaussian prior. When the estimated risk of the negatives falls below -slack, the step climbs back instead of overfitting."""
    w, d = np.zeros(width), np.zeros(dense_pos.shape[1])
    m = [np.zeros(width + len(d)) for _ in range(2)]
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    n_pos, n_unl = len(dense_pos), len(dense_unl)
    back = lambda x, dense, g: np.r_[np.bincount(x[1], g[x[0]], width), dense.T @ g]
    for t in range(1, epochs + 1):
        z_pos = np.bincount(x_pos[0], w[x_pos[1]], n_pos) + dense_pos @ d
        z_unl = np.bincount(x_unl[0], w[x_unl[1]], n_unl) + dense_unl @ d
        p_pos, p_unl = sigmoid(z_pos), sigmoid(z_unl)
        risk = np.logaddexp(0, z_unl).mean() - prior * np.logaddexp(0, z_pos).mean()
        negative = back(x_unl, dense_unl, p_unl / n_unl) - prior * back(x_pos, dense_pos, p_pos / n_pos)
        g = prior * back(x_pos, dense_pos, (p_pos - 1) / n_pos) + negative if risk >= -slack else -negative
        g += decay / n_pos * np.r_[w, d]
        m[0] = 0.9 * m[0] + 0.1 * g
        m[1] = 0.99 * m[1] + 0.01 * g * g
        step = rate * (m[0] / (1 - 0.9**t)) / (np.sqrt(m[1] / (1 - 0.99**t)) + 1e-8)
        w, d = w - step[:width], d - step[width:]
    return w, d


def _picked(ids: DataFrame, most: int) -> DataFrame:
    """At most ``most`` different ids of (id): those of the smallest hashes. A threshold on the hash leaves about twice as many
    before they are made distinct and sorted, so no job sorts or shuffles all ids."""
    n = ids.count()
    reach = F.lit(min(1.0, 2 * most / max(n, 1)) * 2.0**64 - 2.0**63)
    h = F.xxhash64("id")
    near = ids.where(F.col("id").isNotNull() & (h.cast("double") <= reach)).select("id", h.alias("h")).distinct()
    return near.orderBy("h", "id").limit(most).select("id")


def fit(documents: DataFrame, labels: DataFrame, label: str, learn, id_col: str = "doc_id", text_col: str = "text", positives: int = 6000, unlabelled: int = 10000, features: int = 512, min_z: float = 6.0, floor: int = 8, prefix: int = 0) -> PuModel:
    """Learn from at most ``positives`` confirmed positives and ``unlabelled`` other texts (documented bounds; both taken by
    the hash of the id, among the rows for which the column ``learn`` holds; where rows repeat ids, fewer may be found).
    Labels of one id that repeat count once; those that conflict are not trusted and count as none. The class prior is the
    share of positives among the labelled ids that may be learned from. Tokens, and their first ``prefix`` bytes, are kept
    that ``floor`` documents hold and that differ between the two samples by ``min_z`` standard errors, at most ``features``
    of them. Without positives the model scores every text with the prior, or 0.5 if there are no labels."""
    known = labels.where(learn & F.col(label).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.min(label).alias("y"), F.max(label).alias("other")).where("y = other")
    stats = known.agg(F.count("*").alias("n"), F.sum(F.when(F.col("y") == 1, 1).otherwise(0)).alias("p")).first()
    prior = float(np.clip((stats["p"] or 0) / stats["n"], 0.001, 0.999)) if stats["n"] else 0.5
    pos = _sample(documents, _picked(known.where("y = 1").select("id"), positives), id_col, text_col, prefix)
    unl = _sample(documents, _picked(documents.where(learn).select(F.col(id_col).alias("id")), unlabelled), id_col, text_col, prefix)
    flat = np.zeros(DENSE)
    flat[-1] = np.log(prior / (1 - prior))
    if not pos or not unl:
        return PuModel(np.zeros(0, np.uint64), np.zeros(0), flat, prior, prefix)
    (hp, cp), (hu, cu) = _counts(pos), _counts(unl)
    both = np.union1d(hp, hu)
    fp, fu = np.zeros(len(both)), np.zeros(len(both))
    fp[np.searchsorted(both, hp)] = cp
    fu[np.searchsorted(both, hu)] = cu
    rp, ru = fp / len(pos), fu / len(unl)
    pooled = (fp + fu) / (len(pos) + len(unl))
    z = np.abs(rp - ru) / np.sqrt(np.maximum(pooled * (1 - pooled), 1e-9) * (1 / len(pos) + 1 / len(unl)))
    z[fp + fu < floor] = 0
    best = np.argsort(-z, kind="stable")[:features]
    hashes = np.sort(both[best[z[best] >= min_z]])

    def indexed(rows):
        r, c = [], []
        for i, (h, _) in enumerate(rows):
            at = np.searchsorted(hashes, h)
            hit = at[(at < len(hashes)) & (hashes[np.minimum(at, len(hashes) - 1)] == h)] if len(hashes) else np.zeros(0, np.int64)
            r.append(np.full(len(hit), i, np.int32))
            c.append(hit.astype(np.int32))
        return np.concatenate(r), np.concatenate(c)

    del both, fp, fu, rp, ru, pooled, z, hp, cp, hu, cu
    dense_pos, dense_unl = (np.stack([x for _, x in rows]) for rows in (pos, unl))
    x_pos, x_unl = indexed(pos), indexed(unl)
    pos.clear()  # the raw hashes are not held while the weights are learned
    unl.clear()
    pa.default_memory_pool().release_unused()
    w, d = non_negative_fit(x_pos, x_unl, len(hashes), dense_pos, dense_unl, prior)
    return PuModel(hashes, w, d, prior, prefix)


def score(documents: DataFrame, model: PuModel, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, kept columns, score) for every row, over the whole text. A null text scores as an empty one; repeated rows give
    repeated results; an empty input gives none; other columns are ignored."""
    source = documents.select(F.col(id_col).alias("id_"), F.col(text_col).cast("string").alias("text_"), *[F.col(c).alias(f"keep_{c}") for c in keep])
    slots = np.zeros(_SLOTS, bool)
    slots[(model.hashes & np.uint64(_SLOTS - 1)).astype(np.int64)] = True
    slots = np.packbits(slots)

    def rate(b: pa.RecordBatch) -> pa.RecordBatch:
        out, live = np.zeros(b.num_rows), np.unpackbits(slots).astype(bool)
        for first, rows, h, doc, dense in tokens(b.column("text_"), model.prefix):
            z = dense @ model.dense
            at = np.flatnonzero(live[(h & np.uint64(_SLOTS - 1)).astype(np.int64)])
            if len(at):
                f = np.searchsorted(model.hashes, h[at])
                hit = model.hashes[np.minimum(f, len(model.hashes) - 1)] == h[at]
                pairs = np.unique(doc[at][hit] * len(model.hashes) + f[hit])
                z += np.bincount(pairs // len(model.hashes), model.weights[pairs % len(model.hashes)], rows)
            out[first : first + rows] = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
        cols = [c for c in b.schema.names if c != "text_"]
        return pa.RecordBatch.from_arrays([*[b.column(c) for c in cols], pa.array(out)], [*cols, "score"])

    types = {f.name: f.dataType.simpleString() for f in source.schema.fields}
    schema = ", ".join(f"`{c}` {types[c]}" for c in types if c != "text_") + ", score double"
    out = map_batches(source, rate, schema)
    return out.select(F.col("id_").alias(id_col), *[F.col(f"keep_{c}").alias(c) for c in keep], "score")


def classify(documents: DataFrame, labels: DataFrame, label: str, folds: int, held_out: int, threshold: float, **how) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every document; fold ``held_out`` of ``folds`` is not learned from."""
    model = fit(documents, labels, label, fold("doc_id", folds) != held_out, **how)
    out = score(documents, model)
    return out.select("doc_id", (fold("doc_id", folds) == held_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def toxicity(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Toxic texts: confirmed toxic examples against unlabelled text; predicted 1 from a score of 0.7."""
    return classify(documents, labels, "toxic", 3, 1, 0.7, **TOXIC_FEATURES)


def quality(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Good texts: trusted positives against unlabelled web text; predicted 1 from a score of 0.3."""
    return classify(documents, labels, "quality", 5, 0, 0.3)
