"""Exact deduplication by content-defined chunk recipes.

A text is lower-cased (A-Z only), cut into content-defined chunks and described by the ordered list of its
chunks. Chunks get short identifiers that are verified against their SHA-256 digests; two texts are equal when
their lists of verified identifiers are equal. Texts are read once, where they lie: only digests are shuffled.

Defined results: a null text counts as empty; empty texts are equal to each other; rows repeated with the same
id and text are one group of copies, of which one row stays; an empty table gives an empty result; other columns
are ignored, whatever their names. A null id is smaller than any other.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .chunking import Chunker
from .common import materialise, slices, utf8

RECIPE = "doc_id long, text_sha256 binary, chunks array<struct<code:long,digest:binary>>"
_ARROW = pa.schema([("doc_id", pa.int64()), ("text_sha256", pa.binary()), ("chunks", pa.list_(pa.struct([("code", pa.int64()), ("digest", pa.binary())])))])


def recipes(docs: DataFrame, chunker: Chunker | None = None, batch_bytes: int = 8 << 20) -> DataFrame:
    """doc_id, SHA-256 of the normalised text, and the text's ordered chunks as (64-bit code, SHA-256)."""
    chunker = chunker or Chunker()

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", batch_bytes):
            texts = [t.lower() for t in utf8(batch.column("text"))]  # bytes.lower() changes A-Z only
            lists = [[{"code": xxhash.xxh64_intdigest(c) - (1 << 63), "digest": hashlib.sha256(c).digest()} for c in chunks] for chunks in chunker.cut(texts)]
            whole = [row[0]["digest"] if len(row) == 1 else hashlib.sha256(t).digest() for row, t in zip(lists, texts, strict=True)]
            yield pa.record_batch([batch.column("doc_id"), pa.array(whole, pa.binary()), pa.array(lists, _ARROW.field("chunks").type)], schema=_ARROW)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(describe, RECIPE)


def verified_identifiers(chunks: DataFrame) -> DataFrame:
    """(code, digest, variant): digests that share a code are told apart by a variant number.

    (code, variant) therefore names one digest, also where the 64-bit code collides.
    """
    distinct = chunks.groupBy("code", "digest").agg(F.count("*").alias("uses"))
    listed = distinct.groupBy("code").agg(F.array_sort(F.collect_list(F.struct("digest", "uses"))).alias("found"))
    return listed.select("code", F.posexplode("found").alias("variant", "entry")).select("code", F.col("entry.digest").alias("digest"), "variant", F.col("entry.uses").alias("uses"))


def exact_groups(docs: DataFrame, chunker: Chunker | None = None) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256 (hex).

    The row with the largest doc_id of a group stays.
    """
    table = materialise(recipes(docs, chunker), "recipes")
    # Distinct recipes first: a large group of copies shrinks on the map side, before anything is keyed by chunk.
    distinct = materialise(
        table.withColumn("recipe", F.xxhash64("chunks")).groupBy("text_sha256", "recipe", "chunks").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("rows")),
        "distinct-recipes",
    )
    refs = distinct.select("text_sha256", "recipe", F.posexplode("chunks").alias("seq", "chunk")).select("text_sha256", "recipe", "seq", "chunk.code", "chunk.digest")
    names = materialise(verified_identifiers(refs.select("code", "digest")), "identifiers").select("code", "digest", "variant")
    lists = (
        refs.join(names, ["code", "digest"])
        .groupBy("text_sha256", "recipe")
        .agg(F.array_sort(F.collect_list(F.struct("seq", "code", "variant"))).alias("ordered"))
        .select("text_sha256", "recipe", F.transform("ordered", lambda x: F.struct(x["code"].alias("code"), x["variant"].alias("variant"))).alias("identifiers"))
    )
    # Equal ordered lists of verified identifiers are equal texts.
    groups = (
        distinct.select("text_sha256", "recipe", "keep_id", "rows")
        .join(lists, ["text_sha256", "recipe"])
        .groupBy("identifiers")
        .agg(F.max("keep_id").alias("keep_id"), F.sum("rows").alias("group_size"), F.collect_set(F.struct("text_sha256", "recipe")).alias("members"))
        .select("keep_id", "group_size", F.explode("members").alias("m"))
        .select("keep_id", "group_size", "m.text_sha256", "m.recipe")
    )
    groups = materialise(groups, "groups")
    # Rows repeated with the same id are counted before the join and dealt out again after it, one of them kept.
    rows = table.groupBy("doc_id", "text_sha256", F.xxhash64("chunks").alias("recipe")).agg(F.count("*").alias("copies"))
    return (
        materialise(rows, "rows")
        .join(groups, ["text_sha256", "recipe"])
        .select("doc_id", "keep_id", "group_size", F.explode(F.sequence(F.lit(1).cast("long"), "copies")).alias("copy"), "text_sha256")
        .select("doc_id", "keep_id", "group_size", (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("copy") == 1)).alias("kept"), F.lower(F.hex("text_sha256")).alias("text_sha256"))
    )


def drop_copies(docs: DataFrame, chunker: Chunker | None = None) -> DataFrame:
    """``docs`` without exact copies: the row with the largest doc_id of each group stays, with all its columns, whatever their names."""
    kept = exact_groups(docs, chunker).where("kept").select(F.col("doc_id").alias("keep_id"), F.unhex("text_sha256").alias("keep_sha"))
    ascii_lower = F.translate(F.coalesce(F.col("text"), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    keyed = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("id"), F.unhex(F.sha2(ascii_lower.cast("binary"), 256)).alias("sha"))
    joined = keyed.join(kept, keyed["id"].eqNullSafe(kept["keep_id"]) & (keyed["sha"] == kept["keep_sha"]), "left_semi")
    return joined.dropDuplicates(["id", "sha"]).select("row.*")
