"""Word-level BPE: speculate and verify.

A greedy longest match proposes the tokens of each new word. A sequence is the result of merging exactly if every token merges
to itself and every adjacent pair stays a pair when merged alone; that is tested for all pairs of a batch at once, against a
table of known pairs. Only words that fail are merged exactly.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from itertools import pairwise

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

#: A worker keeps the tokens of the words it met lately, in two generations of at most this many words each.
CACHE = 600_000
#: White space of the pre-tokenizer (Unicode White_Space).
WHITE = "\t-\r \x85\xa0  -     　"
_SPLIT = regex.compile(f"[{WHITE}]+")
_ODD = regex.compile("[\x1c-\x1f]|<\\|")


def byte_alphabet() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies: itself, or the next free code point from 256."""
    out, free = [], 256
    for b in range(256):
        if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b:
            out.append(chr(b))
        else:
            out.append(chr(free))
            free += 1
    return out


class WordBpe:
    """Encoder of one vocabulary file with an end-of-word suffix."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.end = model["end_of_word_suffix"]
        self.vocab: dict[str, int] = dict(model["vocab"])
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, m in enumerate(model["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            self.merges[self.vocab[a], self.vocab[b]] = rank, self.vocab[a + b]
        pattern = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pattern = regex.compile(pattern.replace("\\s", WHITE))
        self.bytes = byte_alphabet()
        self.longest = max(map(len, self.vocab))
        self.pairs: dict[int, bool] = {}
        self.alone: dict[int, bool] = {}
        self.known: dict[str, tuple[str, int, str]] = {}
        self.older: dict[str, tuple[str, int, str]] = {}
        self.merged = 0
        self.cut = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None

    def base(self, token: int) -> list[int]:
        """The symbols that merging of a token's own text starts from."""
        name = self.names[token]
        tail = name.endswith(self.end) and len(name) > len(self.end)
        letters = list(name[: -len(self.end)] if tail else name)
        if tail:
            letters[-1] += self.end
        return [self.vocab[x] for x in letters]

    def merge(self, symbols: list[int]) -> list[int]:
        """Exact merging: always the pair of lowest rank, leftmost first; neighbours in a linked list, pairs in a heap."""
        n = len(symbols)
        sym, after, before = symbols[:], list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r[0], i, x, y) for i, (x, y) in enumerate(pairwise(sym)) if (r := self.merges.get((x, y)))]
        heapq.heapify(heap)
        while heap:
            _, i, x, y = heapq.heappop(heap)
            j = after[i]
            if sym[i] != x or j >= n or sym[j] != y:
                continue
            sym[i], sym[j] = self.merges[x, y][1], -1
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            for k in (before[i], i):
                if k >= 0 and after[k] < n and (r := self.merges.get((sym[k], sym[after[k]]))):
                    heapq.heappush(heap, (r[0], k, sym[k], sym[after[k]]))
        return [s for s in sym if s >= 0]

    def propose(self, unit: str) -> list[int]:
        """Greedy longest match."""
        out, i, n, vocab = [], 0, len(unit), self.vocab
        whole = vocab.get(unit + self.end)
        if whole is not None:
            return [whole]
        while i < n:
            if n - i <= self.longest and (t := vocab.get(unit[i:] + self.end)) is not None:
                out.append(t)
                break
            for j in range(min(n - 1, i + self.longest), i, -1):
                t = vocab.get(unit[i:j])
                if t is not None:
                    out.append(t)
                    i = j
                    break
        return out

    def tokenize(self, units: list[str]) -> list[list[int]]:
        """Tokens of byte-level units."""
        found = [self.propose(u) for u in units]
        flat = np.fromiter((t for f in found for t in f), np.int64)
        word = np.repeat(np.arange(len(found)), [len(f) for f in found])
        bad = np.zeros(len(found), bool)
        single, where = np.unique(flat, return_inverse=True)
        for t in single.tolist():
            if t not in self.alone:
                self.alone[t] = self.merge(self.base(t)) == [t]
        bad[word[~np.array([self.alone[t] for t in single.tolist()], bool)[where]]] = True
        inner = word[1:] == word[:-1]
        codes, where = np.unique(flat[:-1][inner] << 20 | flat[1:][inner], return_inverse=True)
        for c in codes.tolist():
            if c not in self.pairs:
                a, b = c >> 20, c & 0xFFFFF
                self.pairs[c] = self.merge(self.base(a) + self.base(b)) == [a, b]
        fine = np.array([self.pairs[c] for c in codes.tolist()], bool)
        bad[word[1:][inner][~fine[where]]] = True
        for i in np.flatnonzero(bad).tolist():
            u = units[i]
            found[i] = self.merge([*[self.vocab[x] for x in u[:-1]], self.vocab[u[-1] + self.end]])
        self.merged += int(bad.sum())
        return found

    def _learn(self, words: list[str]) -> None:
        """Fill the store with words (no white space inside)."""
        if len(self.pairs) > 2 * CACHE:
            self.pairs.clear()
        units: dict[str, int] = {}
        cut = []
        for w in words:
            if not w.isascii():
                w = "".join(c.lower() for c in unicodedata.normalize("NFC", w))
            else:
                w = w.lower()
            cut.append(["".join(map(self.bytes.__getitem__, m.encode())) for m in self.pattern.findall(w)])
            for u in cut[-1]:
                units.setdefault(u, len(units))
        tokens = self.tokenize(list(units)) if units else []
        text = [(" ".join(map(str, t)), len(t), " ".join(map(self.names.__getitem__, t))) for t in tokens]
        for w, c in zip(words, cut, strict=True):
            parts = [text[units[u]] for u in c]
            self.known[w] = parts[0] if len(parts) == 1 else (" ".join(p[0] for p in parts), sum(p[1] for p in parts), " ".join(p[2] for p in parts))

    def words(self, text: str) -> list[str]:
        """Words between white space; special tokens stand as words of their own."""
        if not _ODD.search(text):
            return text.split()
        out = []
        for k, part in enumerate(self.cut.split(text) if self.cut else [text]):
            out += [part] if k % 2 else [w for w in _SPLIT.split(part) if w]
        return out

    def encode(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """(number of tokens, decimal ids joined by a space, decoded text) of each text."""
        cut = [self.words(t) for t in texts]
        need = {w for c in cut for w in c}
        if len(self.known) + len(need) > CACHE:
            self.known, self.older = {}, self.known
        new = []
        for w in need:
            if w not in self.known:
                if (got := self.older.get(w)) is not None:
                    self.known[w] = got
                else:
                    new.append(w)
        plain = [w for w in new if w not in self.special]
        if plain:
            self._learn(plain)
        for w in new:
            if w in self.special:
                self.known[w] = (str(self.special[w]), 1, w)
        out = []
        for c in cut:
            got = [self.known[w] for w in c]
            got = [g for g in got if g[1]]
            out.append((sum([g[1] for g in got]), " ".join([g[0] for g in got]), " ".join([g[2] for g in got])))
        return out


_ENCODERS: dict[str, WordBpe] = {}


def word_encoder(path: str) -> WordBpe:
    if path not in _ENCODERS:
        _ENCODERS[path] = WordBpe(path)
    return _ENCODERS[path]


def encode(documents: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", digests: bool = False) -> DataFrame:
    """(id, n_tokens, ids string, decoded string) of each whole text, or with ``digests`` their SHA-256 instead.

    A null text counts as empty: no tokens, empty strings. Repeated rows give repeated results; an empty input gives none;
    other columns are ignored. The file at ``tokenizer`` must be readable on every executor.
    """
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    names = ("ids_sha256", "decoded_sha256") if digests else ("ids", "decoded")

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        bpe, n, ids, decoded = word_encoder(tokenizer), [], [], []
        for k in range(0, b.num_rows, 128):
            for c, i, d in bpe.encode([t or "" for t in b.column(1).slice(k, 128).to_pylist()]):
                n.append(c)
                ids.append(sha(i) if digests else i)
                decoded.append(sha(d) if digests else d)
        return pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())], ["id", "n_tokens", *names])

    source = documents.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(source, run, f"id long, n_tokens long, {names[0]} string, {names[1]} string").withColumnRenamed("id", id_col)
