"""Language model scoring by deleted interpolation.

The model mixes the uniform distribution, word frequencies and bigram maximum-likelihood estimates. The mixture
weights belong to buckets of the context's frequency and are learned by expectation-maximisation on held-out
counts: every training word is predicted from counts from which its own document has been deleted.

Counts cover all training documents and are exact up to 64-bit hash collisions. Documents are first coded in
blocks: a block's words are numbered in the order of their hashes, so that what is counted, shuffled and answered
are packed key lists (see ``blobs``), a block's every key once, and no single word or bigram can overload a task.
The coded blocks are stored bucketed by block, so the answers join them without moving them again.

Defined results: a null or blank text is one end token; a null id counts as the empty text when folds are dealt;
repeated rows are counted and scored each; without training documents every probability is uniform over the one
unknown token; an empty table gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import hash_words, mix64, pack, pack_sorted, range_bounds, unpack, unpack_sorted
from .common import in_fold, materialise, rows_of, scratch_root, slices, utf8

#: Tokens that no text can hold, because words have no blanks.
BEGIN, END = b" begin", b" end"
BUCKETS = 48
#: Steps of the logarithmic grid on which expectation-maximisation sees probabilities, per factor of e.
GRID = 8

_BLOCK = pa.schema(
    [("block", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("train", pa.list_(pa.bool_())), ("ends", pa.list_(pa.int32())), ("stream", pa.binary()), ("words", pa.binary()), ("n_words", pa.int64()), ("train_tokens", pa.int64())]
)
_BLOCK_SQL = "block long, doc_ids array<long>, train array<boolean>, ends array<int>, stream binary, words binary, n_words long, train_tokens long"


class _Numbers(dict):
    """Numbers words in the order of their first use."""

    def __missing__(self, word: bytes) -> int:
        self[word] = n = len(self)
        return n


def code_blocks(docs: DataFrame, modulus: int, held: int, block_bytes: int) -> DataFrame:
    """Blocks of documents as streams of local word numbers, with the sorted hashes of their words."""

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made, task = 0, TaskContext.get().partitionId()
        numbers, ids, train, ends, parts, held_bytes = _Numbers(), [], [], [], [], 0

        def flush() -> pa.RecordBatch:
            hashes = hash_words(list(numbers))
            order = np.argsort(hashes, kind="stable")
            place = np.empty(len(order), dtype=np.uint32)
            place[order] = np.arange(len(order), dtype=np.uint32)
            stream = place[np.concatenate(parts)]
            lengths = np.diff(ends, prepend=0)
            planes = np.ascontiguousarray(stream.view(np.uint8).reshape(-1, 4).T)
            row = [
                [(task << 24) + made],
                [ids],
                [train],
                [ends],
                [zstandard.ZstdCompressor(3).compress(planes.tobytes())],
                [pack_sorted(hashes[order])],
                [len(order)],
                [int(lengths[np.array(train, dtype=bool)].sum())],
            ]
            return pa.record_batch([pa.array(c, f.type) for c, f in zip(row, _BLOCK, strict=True)], schema=_BLOCK)

        for batch in slices(batches, "text", 1 << 20):
            for doc_id, learn, text in zip(batch.column("doc_id").to_pylist(), batch.column("train").to_pylist(), utf8(batch.column("text")), strict=True):
                words = text.lower().split()  # on the six ASCII blanks; lower() changes A-Z only
                words.append(END)
                parts.append(np.fromiter(map(numbers.__getitem__, words), dtype=np.int32, count=len(words)))
                ids.append(doc_id)
                train.append(learn)
                ends.append((ends[-1] if ends else 0) + len(words))
                held_bytes += len(text) + 8
                if held_bytes >= block_bytes:
                    numbers[BEGIN]
                    yield flush()
                    made += 1
                    numbers, ids, train, ends, parts, held_bytes = _Numbers(), [], [], [], [], 0
        if ids:
            numbers[BEGIN]
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (~in_fold("doc_id", modulus, held)).alias("train"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(code, _BLOCK_SQL)


class _Block:
    """One coded block: tokens, their contexts, and the block's distinct bigrams in the order of their keys."""

    def __init__(self, row: dict) -> None:
        self.ids, self.train = row["doc_ids"], np.array(row["train"], dtype=bool)
        self.ends = np.array(row["ends"], dtype=np.int64)
        self.words = unpack_sorted(row["words"], row["n_words"])
        n = int(self.ends[-1])
        planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(row["stream"]), dtype=np.uint8).reshape(4, n)
        self.token = np.ascontiguousarray(planes.T).view("<u4").reshape(-1).astype(np.int64)
        begin = int(np.searchsorted(self.words, hash_words([BEGIN])[0]))
        self.starts = np.concatenate([[0], self.ends[:-1]])
        self.context = np.concatenate([[0], self.token[:-1]])
        self.context[self.starts] = begin
        self.doc = np.repeat(np.arange(len(self.ends)), np.diff(self.ends, prepend=0))
        self.learn = self.train[self.doc]
        pairs, self.pair = np.unique(self.context << 32 | self.token, return_inverse=True)
        keys = mix64(self.words[pairs >> 32] * np.uint64(3) + mix64(self.words[pairs & 0xFFFFFFFF]))
        order = np.argsort(keys, kind="stable")
        place = np.empty(len(order), dtype=np.int64)
        place[order] = np.arange(len(order))
        self.pair_keys, self.pair = keys[order], place[self.pair]
        self.begin = begin

    def local(self, kind: int) -> tuple[np.ndarray, np.ndarray]:
        """Sorted keys, and how often each occurs in the block's training documents."""
        if kind:
            return self.pair_keys, np.bincount(self.pair[self.learn], minlength=len(self.pair_keys))
        counts = np.bincount(self.token[self.learn], minlength=len(self.words))
        counts[self.begin] = int(self.train.sum())
        return self.words, counts


def ask(blocks: DataFrame, ranges: int) -> DataFrame:
    """(kind, range, block, n, keys, counts): a block's keys of each range; kind 0 words, 1 bigrams."""

    def requests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                block = _Block(row)
                for kind in (0, 1):
                    keys, counts = block.local(kind)
                    at = range_bounds(keys, ranges)
                    out = [(kind, r, row["block"], int(b - a), pack_sorted(keys[a:b]), pack(counts[a:b])) for r, (a, b) in enumerate(zip(at, at[1:], strict=False)) if b > a]
                    columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)]
                    yield pa.record_batch(columns, names=["kind", "range", "block", "n", "keys", "counts"])

    return blocks.mapInArrow(requests, "kind int, range int, block long, n long, keys binary, counts binary")


def answer(table: pa.Table) -> pa.Table:
    """Totals of one range's keys over all blocks, for each block in its own order."""
    rows = sorted(table.to_pylist(), key=lambda r: r["block"])
    keys = np.concatenate([unpack_sorted(r["keys"], r["n"]) for r in rows])
    counts = np.concatenate([unpack(r["counts"], r["n"]) for r in rows]).astype(np.int64)
    distinct, where = np.unique(keys, return_inverse=True)
    totals = np.zeros(len(distinct), dtype=np.int64)
    np.add.at(totals, where, counts)
    mine, at, out = totals[where], 0, []
    for i, r in enumerate(rows):
        out.append((r["kind"], r["range"], r["block"], r["n"], pack(mine[at : at + r["n"]]), int((totals > 0).sum()) if i == 0 else 0))
        at += r["n"]
    columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.int64()), strict=True)]
    return pa.Table.from_arrays(columns, names=["kind", "range", "block", "n", "totals", "distinct"])


def _answered(row: dict) -> tuple[_Block, np.ndarray, np.ndarray]:
    block = _Block(row)
    found: list[list[np.ndarray]] = [[], []]
    for a in sorted(row["answers"], key=lambda a: (a["kind"], a["range"])):
        found[a["kind"]].append(unpack(a["totals"], a["n"]).astype(np.int64))
    return block, np.concatenate(found[0]), np.concatenate(found[1])


def _bucket(context: np.ndarray) -> np.ndarray:
    """0 for a context never seen, else 1 + floor(log2(count))."""
    return np.where(context > 0, np.minimum(BUCKETS - 1, 1 + np.floor(np.log2(np.maximum(context, 1)))), 0).astype(np.int64)


def _own(block: _Block, of: np.ndarray, most: int) -> np.ndarray:
    """For every token, how often its ``of`` occurs in its own document."""
    _, where, n = np.unique(block.doc * most + of, return_inverse=True, return_counts=True)
    return n[where]


def held_out_bins(block: _Block, words: np.ndarray, pairs: np.ndarray, n_tokens: int, n_words: int) -> tuple[np.ndarray, np.ndarray]:
    """Bins (bucket, log word probability, log bigram probability) of the training tokens, their own document deleted."""
    t = block.learn
    lengths = np.diff(block.ends, prepend=0)[block.doc]
    word = words[block.token] - _own(block, block.token, len(block.words))
    pair = pairs[block.pair] - _own(block, block.pair, len(block.pair_keys))
    context = words[block.context] - _own(block, block.context, len(block.words))
    uniform = 1.0 / (n_words + 1)
    with np.errstate(divide="ignore", invalid="ignore"):
        q1 = np.where(word > 0, np.round(GRID * np.log(word / np.maximum(1, n_tokens - lengths) / uniform)) + 512, 0)
        q2 = np.where((pair > 0) & (context > 0), np.round(GRID * np.log(pair / np.maximum(context, 1) / uniform)) + 512, 0)
    code = (_bucket(context) << 22) | (q1.astype(np.int64) << 11) | q2.astype(np.int64)
    return np.unique(code[t], return_counts=True)


def learn_weights(code: np.ndarray, count: np.ndarray, rounds: int = 60) -> np.ndarray:
    """(bucket, part) mixture weights by expectation-maximisation; parts are uniform, word, bigram."""
    bucket, q1, q2 = code >> 22, (code >> 11) & 2047, code & 2047
    p = np.stack([np.ones(len(code)), np.where(q1 > 0, np.exp((q1 - 512) / GRID), 0.0), np.where(q2 > 0, np.exp((q2 - 512) / GRID), 0.0)], axis=1)
    weights = np.full((BUCKETS, 3), 1 / 3)
    weights[0] = (0.5, 0.5, 0.0)  # no bigram estimate in a context never seen
    prior = weights.copy()
    for _ in range(rounds):
        part = weights[bucket] * p
        part *= (count / part.sum(axis=1))[:, None]
        new = np.stack([np.bincount(bucket, part[:, k], BUCKETS) for k in range(3)], axis=1) + prior
        weights = new / new.sum(axis=1, keepdims=True)
    return weights


def _scores(block: _Block, words: np.ndarray, pairs: np.ndarray, n_tokens: int, n_words: int, weights: np.ndarray) -> pa.RecordBatch:
    c, context = words[block.token], words[block.context]
    mixed = weights[_bucket(context)]
    p = mixed[:, 0] / (n_words + 1) + mixed[:, 1] * c / max(1, n_tokens) + mixed[:, 2] * pairs[block.pair] / np.maximum(context, 1)
    if not n_tokens:
        p = np.full(len(c), 1.0 / (n_words + 1))
    total = lambda x: np.add.reduceat(x, block.starts)
    columns = [
        pa.array(block.ids, pa.int64()),
        pa.array(~block.train),
        pa.array(np.diff(block.ends, prepend=0).astype(np.int64)),
        pa.array(total((c > 0).astype(np.int64))),
        pa.array(np.full(len(block.ids), n_tokens, dtype=np.int64)),
        pa.array(total(np.log10((c + 1) / (n_tokens + 1 * (n_words + 1))))),
        pa.array(total(np.log10(p))),
    ]
    return pa.record_batch(columns, names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])


def score(docs: DataFrame, modulus: int = 7, held: int = 2, block_bytes: int = 6 << 20, keys_per_range: int = 1 << 20) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    name = f"coded_{uuid.uuid4().hex}"
    buckets = max(1, min(parts, 100_000))
    coded = code_blocks(docs, modulus, held, block_bytes)
    coded.write.bucketBy(buckets, "block").sortBy("block").option("compression", "uncompressed").option("path", f"{scratch_root(spark)}/{name}").saveAsTable(name)
    atexit.register(_forget, spark, name)
    blocks = spark.table(name)

    sums = blocks.agg(F.sum("train_tokens"), F.sum(F.element_at("ends", -1)), F.sum(F.size(F.filter("train", lambda t: t)))).first()
    n_tokens, tokens, learned = (int(x or 0) for x in sums)
    ranges = max(parts, -(-tokens // keys_per_range))
    answers = materialise(ask(blocks, ranges).groupBy("kind", "range").applyInArrow(answer, "kind int, range int, block long, n long, totals binary, distinct long"), "answers")
    n_words = int(answers.where("kind = 0").agg(F.sum("distinct")).first()[0] or 0) - (1 if learned else 0)  # BEGIN is no word

    given = answers.groupBy("block").agg(F.collect_list(F.struct("kind", "range", "n", "totals")).alias("answers"))
    joined = blocks.join(given.hint("merge"), "block")  # both sides by block: the bucketed blocks stay where they are

    def bins(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                code, count = held_out_bins(*_answered(row), n_tokens, n_words)
                yield pa.record_batch([pa.array(code, pa.int64()), pa.array(count, pa.int64())], names=["code", "n"])

    binned = joined.mapInArrow(bins, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect()  # at most one row a cell of the grid
    weights = learn_weights(np.array([r.code for r in binned], dtype=np.int64), np.array([r.n for r in binned], dtype=float))

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                yield _scores(*_answered(row), n_tokens, n_words, weights)

    return joined.mapInArrow(scored, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def _forget(spark, name: str) -> None:
    try:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    except Exception:  # the session has already ended, and with it its catalog
        return
