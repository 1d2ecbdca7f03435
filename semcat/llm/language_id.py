"""Language identification with hyperdimensional profiles.

Every letter class has a random vector of +1 and -1. A letter trigram is the product (binding) of its three letter vectors,
rotated by their places; a text is the sum (bundle) of its trigrams' vectors, and so is a language's prototype. A document
goes to the language whose prototype has the largest cosine with it. The dot product of a bundle with a prototype is the sum
of its trigrams' dot products, so executors look those up in one table instead of building long vectors.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, fold, map_batches, map_stream, utf8

#: Letter classes; class 0 is everything that is not a letter. Trigrams: CLASSES ** 3.
CLASSES = 64
_TABLE: list[np.ndarray] = []


def letter_classes() -> np.ndarray:
    """Class of each code point, lower-cased first: a-z have their own, other letters share the rest by code point."""
    if not _TABLE:
        t = np.zeros(0x110000, np.uint8)
        for c in range(0x20000):
            s = chr(c)
            if s.isalpha():
                low = ord(s.lower()[0])
                t[c] = low - 96 if 97 <= low <= 122 else 27 + low % (CLASSES - 27)
        rest = np.arange(0x20000, 0x32400)
        t[rest] = 27 + rest % (CLASSES - 27)  # ideographs
        _TABLE.append(t)
    return _TABLE[0]


def trigrams(col: pa.Array):
    """For runs of documents: (first row, rows, trigram codes, document of each trigram). A trigram stands at each letter;
    what is not a letter, and the end of the text, counts as class 0 on its sides."""
    data, offsets, _ = utf8(col)
    table = letter_classes()
    for i, j in blocks(offsets):
        raw = data[offsets[i] : offsets[j]]
        points = np.frombuffer(raw.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
        cls = table[np.minimum(points, 0x10FFFF)].astype(np.int32)
        ends = np.r_[0, np.cumsum((raw & 0xC0) != 0x80)][offsets[i : j + 1] - offsets[i]]
        before, after = np.r_[np.int32(0), cls[:-1]], np.r_[cls[1:], np.int32(0)]
        inner = ends[(ends > 0) & (ends < len(cls))]
        before[inner] = 0
        after[inner - 1] = 0
        at = np.flatnonzero(cls)
        yield i, j - i, ((before * CLASSES + cls) * CLASSES + after)[at], np.searchsorted(ends, at, "right") - 1


@dataclass
class LanguageModel:
    """languages, and for each trigram code its dot product with each unit prototype."""

    languages: list[str]
    table: np.ndarray


def fit(documents: DataFrame, text_col: str = "text", lang_col: str = "lang", dims: int = 2048, seed: int = 7) -> LanguageModel:
    """Prototypes from all texts with a non-null language. Executors count trigrams; the driver gets at most
    CLASSES ** 3 counts for each language, whatever the number of documents."""

    def count(batches):
        acc: dict[str, np.ndarray] = {}
        for b in batches:
            langs = b.column(1).to_pylist()
            for first, rows, codes, doc in trigrams(b.column(0)):
                own = np.array(langs[first : first + rows], object)
                for lang in set(own):
                    hit = (own == lang)[doc] if len(doc) else np.zeros(0, bool)
                    acc.setdefault(lang, np.zeros(CLASSES**3, np.int64))
                    acc[lang] += np.bincount(codes[hit], minlength=CLASSES**3)
        for lang, x in acc.items():
            at = np.flatnonzero(x)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(x[at])], ["lang", "gram", "n"])

    known = documents.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(text_col).cast("string"), F.col(lang_col).cast("string"))
    counts = map_stream(known, count, "lang string, gram int, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).toPandas()
    languages = sorted(set(counts["lang"]))
    table = np.zeros((CLASSES**3, max(1, len(languages))), np.float32)
    grams = np.unique(counts["gram"].to_numpy(np.int64)) if len(counts) else np.zeros(0, np.int64)
    if len(grams):
        letters = np.where(np.random.default_rng(seed).integers(0, 2, (CLASSES, dims)) > 0, 1, -1).astype(np.int8)
        first, second = np.roll(letters, 2, 1), np.roll(letters, 1, 1)
        weight = np.zeros((len(grams), len(languages)), np.float32)
        col = counts["lang"].map({x: i for i, x in enumerate(languages)}).to_numpy()
        weight[np.searchsorted(grams, counts["gram"].to_numpy()), col] = counts["n"].to_numpy(float)

        def vectors(g):
            return (first[g // CLASSES**2] * second[g // CLASSES % CLASSES] * letters[g % CLASSES]).astype(np.float32)

        proto = sum(weight[k : k + 2048].T @ vectors(grams[k : k + 2048]) for k in range(0, len(grams), 2048))
        proto /= np.maximum(np.linalg.norm(proto, axis=1, keepdims=True), 1e-12)
        for k in range(0, len(grams), 2048):
            g = grams[k : k + 2048]
            table[g] = vectors(g) @ proto.T
    return LanguageModel(languages, table)


def predict(documents: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), sharpness: float = 12.0) -> DataFrame:
    """(id, lang_pred, score) and the columns in ``keep`` for every row.

    lang_pred: the language with the largest cosine, ties to the first in order of names; ``und`` with score 0 if the text is
    null, has no letter, or no language was learned. score: the winner's share of exp(sharpness * cosine / best cosine).
    Repeated rows give repeated results; an empty input gives none; other columns are ignored.
    """
    names, table = model.languages, model.table
    source = documents.select(F.col(id_col).alias("id_"), F.col(text_col).cast("string").alias("text_"), *[F.col(c).alias(f"keep_{c}") for c in keep])

    def score(b: pa.RecordBatch) -> pa.RecordBatch:
        pred, value = ["und"] * b.num_rows, np.zeros(b.num_rows)
        for first, rows, codes, doc in trigrams(b.column("text_")):
            if not len(codes) or not names:
                continue
            docs, at = np.unique(doc, return_index=True)
            cosine = np.add.reduceat(table[codes], at, axis=0).astype(np.float64)
            best = cosine.argmax(1)
            top = np.maximum(cosine.max(1), 1e-9)
            share = np.exp(sharpness * (np.clip(cosine / top[:, None], -1, 1) - 1))
            value[first + docs] = share[np.arange(len(docs)), best] / share.sum(1)
            for d, x in zip(docs.tolist(), best.tolist(), strict=True):
                pred[first + d] = names[x]
        cols = [c for c in b.schema.names if c != "text_"]
        return pa.RecordBatch.from_arrays([*[b.column(c) for c in cols], pa.array(pred, pa.string()), pa.array(np.clip(value, 0, 1))], [*cols, "lang_pred", "score"])

    types = {f.name: f.dataType.simpleString() for f in source.schema.fields}
    schema = ", ".join(f"`{c}` {types[c]}" for c in types if c != "text_") + ", lang_pred string, score double"
    out = map_batches(source, score, schema)
    return out.select(F.col("id_").alias(id_col), *[F.col(f"keep_{c}").alias(c) for c in keep], "lang_pred", "score")


def identify(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", folds: int = 5) -> DataFrame:
    """Learn from the folds other than 0, predict every row: (id, held_out, lang_pred, score)."""
    model = fit(documents.where(fold(id_col, folds) != 0), text_col, lang_col)
    out = predict(documents, model, id_col, text_col)
    return out.select(id_col, (fold(id_col, folds) == 0).alias("held_out"), "lang_pred", "score")
