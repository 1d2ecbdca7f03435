"""Media columns with content-defined chunks.

A text's padded payload becomes an 8-bit sample file (a header and one byte a sample). The file is cut where a rolling gear hash
of the last 32 bytes meets a mask, so equal passages give equal chunks wherever they stand. Digests of all chunks but the
header, which is always the first, are counted by Spark; chunks that occur once are kept with their own media row, shared chunks once in a chunk table, chosen by joins of
digests. Media are rebuilt from ordered chunk lists, and every chunk and file is verified by its digest when read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import FILTER_BITS, map_batches, map_stream, materialise, membership_filter, mix, passes

#: Chunk sizes in bytes: least, mean beyond the least (a power of two), most.
LEAST, MEAN, MOST = 512, 2048, 16384
RATE = 8000
_GEAR = (mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F)) >> np.uint64(32)).astype(np.uint32)


def sample_file(payload: bytes) -> bytes:
    """The payload as a mono WAV file of unsigned 8-bit samples; lossless, 44 bytes of header."""
    n = len(payload)
    return struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + n, b"WAVE", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8, b"data", n) + payload


def samples(media: bytes) -> bytes:
    """The samples of such a file; raises where the header and the length do not agree."""
    kind, whole, wave, *_, bits, data, n = struct.unpack("<4sI4s4sIHHIIHH4sI", media[:44])
    if (kind, wave, bits, data) != (b"RIFF", b"WAVE", 8, b"data") or whole != 36 + n or len(media) != 44 + n:
        raise ValueError("not a sample file of this kind")
    return media[44:]


def padded(raw: bytes) -> bytes:
    """Zero bytes up to a positive multiple of 64."""
    return raw + b"\0" * (-len(raw) % 64 if raw else 64)


def cut_points(data: np.ndarray) -> list[int]:
    """Ends of the chunks of one file. The gear hash of 32 bytes is built by doubling windows; the header is a chunk."""
    h = _GEAR[data]
    for k in range(5):
        s = 1 << k
        if len(h) > s:
            h[s:] += h[:-s] << np.uint32(s)
    hits = (np.flatnonzero(h >> np.uint32(32 - (MEAN.bit_length() - 1)) == 0) + 1).tolist()
    out, at, k, n = [min(44, len(data))], min(44, len(data)), 0, len(data)
    while at < n:
        while k < len(hits) and hits[k] < at + LEAST:
            k += 1
        end = min(hits[k] if k < len(hits) else n, at + MOST, n)
        out.append(end)
        at = end
    return out


def chunks(media: bytes) -> list[bytes]:
    at, out = 0, []
    for end in cut_points(np.frombuffer(media, np.uint8)):
        out.append(media[at:end])
        at = end
    return out


def digest(chunk: bytes) -> bytes:
    return hashlib.blake2b(chunk, digest_size=16).digest()


#: An entry of a chunk list: the digest's halves and the size.
_ENTRY = "<qqI"


def entries(parts: list[bytes]) -> bytes:
    return b"".join(digest(c) + struct.pack("<I", len(c)) for c in parts)


def store(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """Write the media of all texts: (media, chunk table), both stored Parquet in the shared folder.

    media: rid, id, n_bytes, list (ordered entries), shared (one byte a chunk), n_shared, own (compressed bytes of the chunks
    that are not shared). chunk table: d1, d2, bytes; one row for each shared digest.
    """
    source = documents.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("raw"))

    def list_digests(b: pa.RecordBatch) -> pa.RecordBatch:
        d = [x for raw in b.column(0) for x in struct.iter_unpack(_ENTRY, entries(chunks(sample_file(padded(raw.as_py() or b"")))[1:]))]
        return pa.RecordBatch.from_arrays([pa.array([x[k] for x in d], pa.int64()) for k in range(2)], ["d1", "d2"])

    counted = map_batches(source.select("raw"), list_digests, "d1 long, d2 long").groupBy("d1", "d2").agg(F.count("*").alias("n"))
    # a bitmap of fixed size: a chunk it lets through by chance is only stored in the chunk table instead of with its media
    bits = membership_filter(counted.where("n > 1"), "d1", hashed=True)

    def split(b: pa.RecordBatch) -> pa.RecordBatch:
        cols: list[list] = [[] for _ in range(9)]
        pack = zstandard.ZstdCompressor(level=3)
        here: set[bytes] = set()
        for rid, i, raw in zip(b.column("rid").to_pylist(), b.column("id").to_pylist(), b.column("raw"), strict=True):
            raw = raw.as_py() or b""
            parts = chunks(sample_file(padded(raw)))
            row = entries(parts)
            d = list(struct.iter_unpack(_ENTRY, row))
            flag = passes(bits, np.array([x[0] % FILTER_BITS for x in d], np.int64)).tolist()
            flag[0] = False  # the header says no more than the size
            for k, f in enumerate(flag):
                key = row[20 * k : 20 * k + 16]
                if f and key not in here:  # a batch sends a chunk once
                    here.add(key)
                    for c, v in zip(cols, (rid, None, None, None, None, None, d[k][0], d[k][1], pack.compress(parts[k])), strict=True):
                        c.append(v)
            own = pack.compress(b"".join(p for p, f in zip(parts, flag, strict=True) if not f))
            for c, v in zip(cols, (rid, i, len(raw), row, bytes(flag), sum(flag), None, None, own), strict=True):
                c.append(v)
        types = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int32(), pa.int64(), pa.int64(), pa.binary()]
        names = ["rid", "id", "n_bytes", "list", "shared", "n_shared", "d1", "d2", "own"]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    rows = source.withColumn("rid", F.monotonically_increasing_id())
    rows = materialise(map_batches(rows, split, "rid long, id long, n_bytes long, list binary, shared binary, n_shared int, d1 long, d2 long, own binary"), "media")
    offered = rows.where("list is null").select("rid", "d1", "d2", F.col("own").alias("bytes"))
    owner = offered.groupBy("d1", "d2").agg(F.min("rid").alias("rid"))
    kept = offered.join(owner, ["d1", "d2", "rid"], "left_semi").dropDuplicates(["d1", "d2"])
    return rows.where("list is not null").drop("d1", "d2"), materialise(kept.select("d1", "d2", "bytes"), "chunks")


def rebuild(media: DataFrame, table: DataFrame) -> DataFrame:
    """(id, n_bytes, media binary): files put together from their chunk lists; raises where a chunk fails its digest."""
    whole = media.where("n_shared = 0").withColumn("parts", F.lit(None).cast("array<struct<k:int,bytes:binary>>"))
    need = media.where("n_shared > 0")
    refs = map_batches(need.select("rid", "list", "shared"), _references, "rid long, k int, d1 long, d2 long")
    parts = refs.join(table, ["d1", "d2"]).groupBy("rid").agg(F.collect_list(F.struct("k", "bytes")).alias("parts"))
    rest = need.join(parts, "rid", "left")

    def build(batches):
        unpack = zstandard.ZstdDecompressor()
        for b in batches:
            for first in range(0, b.num_rows, 64):
                t = b.slice(first, 64)
                files = []
                for row, shared, own, got in zip(*(t.column(c).to_pylist() for c in ("list", "shared", "own", "parts")), strict=True):
                    data, have, mine, at = unpack.decompress(own), {p["k"]: unpack.decompress(p["bytes"]) for p in got or []}, [], 0
                    for k, (_, _, size) in enumerate(struct.iter_unpack(_ENTRY, row)):
                        mine.append(have[k] if shared[k] else data[at : at + size])
                        at += 0 if shared[k] else size
                    if entries(mine) != row:
                        raise ValueError("a chunk does not match its digest")
                    files.append(b"".join(mine))
                yield pa.RecordBatch.from_arrays([t.column("id"), t.column("n_bytes"), pa.array(files, pa.binary())], ["id", "n_bytes", "media"])

    cols = ["id", "n_bytes", "list", "shared", "own", "parts"]
    return map_stream(whole.select(cols).unionByName(rest.select(cols)), build, "id long, n_bytes long, media binary")


def _references(b: pa.RecordBatch) -> pa.RecordBatch:
    out: list[tuple] = []
    for r, row, shared in zip(*(b.column(c).to_pylist() for c in ("rid", "list", "shared")), strict=True):
        out += [(r, k, d1, d2) for k, (d1, d2, _) in enumerate(struct.iter_unpack(_ENTRY, row)) if shared[k]]
    types = [pa.int64(), pa.int32(), pa.int64(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], t) for k, t in enumerate(types)], ["rid", "k", "d1", "d2"])


def feature(payload: bytes) -> str:
    """A short description of the samples: mean, root mean square about the middle, share of crossings of the middle, and a
    histogram of the samples' upper two bits; integers only, so it is the same everywhere."""
    x = np.frombuffer(payload, np.uint8).astype(np.int64) - 128
    cross = int(((x[1:] >= 0) != (x[:-1] >= 0)).sum())
    hist = np.bincount((x + 128) >> 6, minlength=4)
    return f"n={len(x)};mean_milli={int(x.sum()) * 1000 // len(x)};power={int((x * x).sum()) // len(x)};cross={cross};hist=" + ",".join(map(str, hist.tolist()))


def media_columns(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store every whole text as media, read the media back, and describe what was read.

    (id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature). A null or empty text is a
    payload of 64 zero bytes; repeated rows give repeated results; an empty input gives none; other columns are ignored.
    """
    files = rebuild(*store(documents, id_col, text_col))

    def describe(b: pa.RecordBatch) -> pa.RecordBatch:
        cols: list[list] = [[] for _ in range(6)]
        for m in b.column("media"):
            m = m.as_py()
            p = samples(m)
            for c, v in zip(cols, (len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]), len(m), hashlib.sha256(m).hexdigest(), feature(p)), strict=True):
                c.append(v)
        names = ["payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
        types = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([b.column("id"), b.column("n_bytes"), *[pa.array(c, t) for c, t in zip(cols, types, strict=True)]], ["id", "n_bytes", *names])

    out = map_batches(files, describe, "id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
    return out.withColumnRenamed("id", id_col)
