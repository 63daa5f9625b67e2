"""Token counts by a public tokenizer, in Arrow functions that return lengths only.

Batches are balanced by bytes, not by rows, and a long text is split where the pre-tokenizer always splits, so
that its parts have as many tokens as the whole.

Defined results: a null or empty text has 0 bytes and 0 tokens; repeated rows are counted each; an empty table
gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

#: A space or line feed between two letters of any script begins a token of its own in the byte-level pre-tokenizer.
_SAFE = re.compile(r"(?<=[^\W\d_])[ \n](?=[^\W\d_])")
_loaded: dict[str, object] = {}


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _tokenizer(path: str):
    if path not in _loaded:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        tokenizer.no_truncation()
        tokenizer.no_padding()
        _loaded[path] = tokenizer
    return _loaded[path]


def safe_parts(text: str, about: int = 16384) -> list[str]:
    """Consecutive parts of at least ``about`` characters, cut at safe boundaries only.

    A text without such a boundary stays whole.
    """
    parts, begin = [], 0
    while len(text) - begin > about:
        m = _SAFE.search(text, begin + about)
        while m and not (text[m.start() - 1].isalpha() and text[m.end()].isalpha()):  # a number that is no digit, as a superscript, is no letter
            m = _SAFE.search(text, m.end())
        if not m:
            break
        parts.append(text[begin : m.start()])
        begin = m.start()
    parts.append(text[begin:])
    return parts


def count_tokens(docs: DataFrame, tokenizer_path: str | None = None, limit: int = 512, batch_bytes: int = 1 << 20) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_tokens, over_limit (n_tokens above ``limit``)."""
    path = tokenizer_path or default_tokenizer()

    def lengths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _tokenizer(path).encode_batch_fast
        for batch in slices(batches, "text", batch_bytes):
            owners, parts = [], []
            texts = batch.column("text").to_pylist()
            for i, text in enumerate(texts):
                for part in safe_parts(text or ""):
                    owners.append(i)
                    parts.append(part)
            counts = [0] * len(texts)
            for i, encoding in zip(owners, encode(parts, add_special_tokens=False), strict=True):
                counts[i] += len(encoding)
            sizes = pc.fill_null(pc.binary_length(batch.column("text")), 0).cast(pa.int64())
            yield pa.record_batch([batch.column("doc_id"), sizes, pa.array(counts, pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    counted = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lengths, "doc_id long, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
