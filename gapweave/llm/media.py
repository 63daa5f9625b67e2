"""Media columns whose payloads are stored as content-defined chunks.

A text's UTF-8 bytes, zero-padded to a positive multiple of 64, become the 8-bit samples of a mono WAV file. The
file, header and all, is cut by a rolling gear hash; a manifest keeps a medium's ordered chunk digests, and a chunk
store keeps every chunk once, deduplicated by digest in Spark. Media are rebuilt by joining manifests with the store,
verified against the SHA-256 of the whole file, and the stored bytes are read back through a WAV reader.

The bytes are shuffled once, compressed, to meet equal chunks; only media of several chunks move again, to be
put in order. Media that are equal as a whole are rebuilt once.

Defined results: a null text counts as empty, its payload is 64 zero bytes; equal texts give equal values; repeated
rows are returned each; an empty table gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .chunking import Chunker
from .common import materialise, slices, utf8

UNIT = 64
RATE = 8000
#: Chunks are large, so that most texts are one chunk and move once.
CHUNKER = Chunker(least=4096, bits=14, most=1 << 18)
#: A chunk that many media share is kept in up to this many copies, so that no single task serves all of them.
SALTS = 16
_RESULT = "media_sha256 binary, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, feature string"


def payload_of(text: bytes) -> bytes:
    return text + bytes(-len(text) % UNIT if text else UNIT)


def to_media(payload: bytes) -> bytes:
    """The payload as the samples of an 8-bit mono WAV file."""
    file = io.BytesIO()
    with wave.open(file, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(payload)
    return file.getvalue()


def from_media(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as w:
        if (w.getnchannels(), w.getsampwidth()) != (1, 1):
            raise ValueError("not an 8-bit mono file")
        return w.readframes(w.getnframes())


def feature_of(samples: bytes) -> str:
    """Sum, sum of squares about the centre, crossings of the centre, least and greatest sample."""
    x = np.frombuffer(samples, dtype=np.uint8).astype(np.int64) - 128
    return f"sum={x.sum()};energy={(x * x).sum()};crossings={int(((x[1:] >= 0) != (x[:-1] >= 0)).sum())};min={x.min()};max={x.max()}"


def _digest(chunk: bytes) -> bytes:
    return hashlib.blake2b(chunk, digest_size=16).digest()


def _salt(media_sha256: bytes) -> int:
    return media_sha256[0] % SALTS


def manifests(docs: DataFrame, chunker: Chunker = CHUNKER, batch_bytes: int = 4 << 20) -> DataFrame:
    """doc_id, n_bytes, media_sha256, chunks (ordered digests)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", batch_bytes):
            texts = utf8(batch.column("text"))
            media = [to_media(payload_of(t)) for t in texts]
            shas = [hashlib.sha256(m).digest() for m in media]
            chunks = [[_digest(c) for c in cs] for cs in chunker.cut(media)]
            columns = [batch.column("doc_id"), pa.array(map(len, texts), pa.int64()), pa.array(shas, pa.binary()), pa.array(chunks, pa.list_(pa.binary()))]
            yield pa.record_batch(columns, names=["doc_id", "n_bytes", "media_sha256", "chunks"])

    return _texts(docs).mapInArrow(run, "doc_id long, n_bytes long, media_sha256 binary, chunks array<binary>")


def chunk_store(docs: DataFrame, chunker: Chunker = CHUNKER, batch_bytes: int = 4 << 20) -> DataFrame:
    """digest, salt, data (compressed): every distinct chunk, once for each salt that asks for it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer, seen = zstandard.ZstdCompressor(3), set()
        for batch in slices(batches, "text", batch_bytes):
            media = [to_media(payload_of(t)) for t in utf8(batch.column("text"))]
            out: list[list] = [[], [], []]
            for medium, chunks in zip(media, chunker.cut(media), strict=True):
                salt = _salt(hashlib.sha256(medium).digest())
                for chunk in chunks:
                    key = (_digest(chunk), salt)
                    if key in seen:
                        continue
                    if len(seen) < 500_000:  # a task that has seen more sends some chunks twice
                        seen.add(key)
                    for column, value in zip(out, (*key, packer.compress(chunk)), strict=True):
                        column.append(value)
            yield pa.record_batch([pa.array(c, t) for c, t in zip(out, (pa.binary(), pa.int32(), pa.binary()), strict=True)], names=["digest", "salt", "data"])

    rows = _texts(docs).mapInArrow(run, "digest binary, salt int, data binary")
    return rows.groupBy("digest", "salt").agg(F.any_value("data").alias("data"))


def _texts(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def _read_back(sha256: bytes, media: bytes) -> tuple:
    if hashlib.sha256(media).digest() != sha256:
        raise ValueError(f"medium {sha256.hex()} does not match its manifest")
    samples = from_media(media)
    return sha256, len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-UNIT:]), len(media), feature_of(samples)


def _result(rows: list[tuple]) -> list[pa.Array]:
    types = (pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string())
    return [pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 6, types, strict=True)]


def rebuild(manifest: DataFrame, store: DataFrame) -> DataFrame:
    """One row per distinct medium, read back from its chunks: the columns of ``_RESULT``."""
    media = manifest.groupBy("media_sha256").agg(F.first("chunks").alias("chunks"))
    salt = F.pmod(F.conv(F.hex(F.substring("media_sha256", 1, 1)), 16, 10).cast("int"), F.lit(SALTS))
    refs = media.select("media_sha256", F.size("chunks").alias("n"), salt.alias("salt"), F.posexplode("chunks").alias("seq", "digest"))
    pieces = materialise(refs, "references").join(store, ["digest", "salt"]).select("media_sha256", "n", "seq", "data")

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Media of one chunk are read back at once; the chunks of others pass on."""
        names = ["media_sha256", "n", "seq", "data", "done"]
        for batch in batches:
            done: list[dict | None] = []
            data = batch.column("data").to_pylist()
            for i, (sha, n) in enumerate(zip(batch.column("media_sha256").to_pylist(), batch.column("n").to_pylist(), strict=True)):
                if n == 1:
                    done.append(dict(zip(("bytes", "sha", "crc", "media", "feature"), _read_back(sha, _open(data[i]))[1:], strict=True)))
                    data[i] = None
                else:
                    done.append(None)
            kind = pa.struct([("bytes", pa.int64()), ("sha", pa.string()), ("crc", pa.int64()), ("media", pa.int64()), ("feature", pa.string())])
            yield pa.record_batch([batch.column("media_sha256"), batch.column("n"), batch.column("seq"), pa.array(data, pa.binary()), pa.array(done, kind)], names=names)

    done_type = "struct<bytes:long,sha:string,crc:long,media:long,feature:string>"
    first = pieces.mapInArrow(whole, f"media_sha256 binary, n int, seq int, data binary, done {done_type}")
    ordered = first.groupBy("media_sha256").agg(F.first("done").alias("done"), F.array_sort(F.collect_list(F.when(F.col("done").isNull(), F.struct("seq", "data")))).alias("parts"))

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for i in range(batch.num_rows):
                sha, done = batch.column("media_sha256")[i].as_py(), batch.column("done")[i].as_py()
                if done:
                    rows.append((sha, done["bytes"], done["sha"], done["crc"], done["media"], done["feature"]))
                else:
                    rows.append(_read_back(sha, b"".join(_open(p["data"]) for p in batch.column("parts")[i].as_py())))
            yield pa.record_batch(_result(rows), names=["media_sha256", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "feature"])

    return ordered.mapInArrow(joined, _RESULT)


def _open(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data)


def media_features(docs: DataFrame, chunker: Chunker = CHUNKER) -> DataFrame:
    """One row per document: doc_id, n_bytes, payload and media digests and sizes, and a feature of the samples read back."""
    manifest = materialise(manifests(docs, chunker), "manifests")
    found = materialise(rebuild(manifest, chunk_store(docs, chunker)), "media")
    rows = manifest.select("doc_id", "n_bytes", "media_sha256").join(found.withColumnRenamed("media_sha256", "_sha"), F.col("media_sha256") == F.col("_sha"))
    return rows.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", F.lower(F.hex("media_sha256")).alias("media_sha256"), "feature")
