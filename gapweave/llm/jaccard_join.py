"""Similarity join on word n-gram sets, with adaptive multi-match prefixes.

Two sets link when their Jaccard similarity reaches a threshold. All sets share one order of shingles (by hash). If
two sets link, then for every l their first n - need + l shingles have l in common, where need is the overlap that
the threshold asks of a set of n. A document may therefore leave k frequent, costly shingles out of its posting
list if it takes l = k + m: at least m of the others are shared with any partner. Each document picks the l that its
own shingles' document frequencies make cheapest, and a pair must share as many posted shingles as the side with the
shorter prefix asks before the full sets are compared. A document whose longest prefix holds too few shingles that any
other set has is linked with nothing and posts none.

What keeps the work linear: equal sets are one node from the start; a list of documents is first compared with one
pivot, the document whose shingles are the most frequent in the lists, then with a few others; only pairs from
different components of the links found so far are left for the exact pass. No link between different sets is lost
for the components, and a large group of near copies costs its size, not its square.

Defined results: a null, empty or blank text has an empty set and is linked with nothing, its component is itself;
rows repeated with the same id are one node; null ids are one node too, smaller than any other; an empty table gives
an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import atexit
import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import mix64, pack, pack_sorted, range_bounds, unpack, unpack_sorted
from .common import materialise, rows_of, scratch_root, slices, utf8
from .components import connected_components
from .interpolation import _forget

#: Ids sent to all executors at most; beyond, texts are joined by shuffling.
BROADCAST_IDS = 500_000
NO_ID = -(1 << 63)
#: Shingles are counted and posted by the upper 48 bits of their hashes, which travel in fewer bytes. Two that fall
#: together have one frequency and one list in every document, so no link is lost; the sets compared are of whole hashes.
KEY_SHIFT = np.uint64(16)
KEY_BITS = ~np.uint64(0) << KEY_SHIFT


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 150_000:  # words seldom come back after so many others, and a worker has little memory
            self.clear()
        self[word] = h = xxhash.xxh64_intdigest(word)
        return h


def shingle_sets(texts: list[bytes], width: int, hashes: _Hashes) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text: runs of ``width`` words, or all words if there are fewer."""
    words = [t.lower().split() for t in texts]
    counts = np.array([len(w) for w in words], dtype=np.int64)
    h = np.fromiter((hashes[w] for ws in words for w in ws), dtype=np.uint64, count=int(counts.sum()))
    starts = np.concatenate([[0], np.cumsum(counts)[:-1]]) if len(counts) else counts
    whole = _codes(h, width) if len(h) >= width else np.zeros(0, dtype=np.uint64)  # those across two texts are never used
    out = []
    for a, n in zip(starts.tolist(), counts.tolist(), strict=True):
        if n >= width:
            out.append(np.unique(whole[a : a + n - width + 1]))
        else:
            out.append(_codes(h[a : a + n], n) if n else np.zeros(0, dtype=np.uint64))
    return out


def _codes(h: np.ndarray, k: int) -> np.ndarray:
    code = np.full(len(h) - k + 1, k, dtype=np.uint64)
    for i in range(k):
        code = mix64(code * np.uint64(0x9E3779B97F4A7C15) + h[i : len(h) - k + 1 + i])
    return code


def needed(n: int, percent: int) -> int:
    """The least overlap of a set of n with any partner: similarity s asks for s of the union, so of n."""
    return -(-percent * n // 100)


def describe(docs: DataFrame, width: int, percent: int, most_l: int, batch_bytes: int = 2 << 20) -> DataFrame:
    """doc_id, n_shingles, 128-bit signature of the set, and its longest prefix (packed hashes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _Hashes()
        for batch in slices(batches, "text", batch_bytes):
            sets = shingle_sets(utf8(batch.column("text")), width, hashes)
            signatures = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets]
            prefixes = [s[: len(s) - needed(len(s), percent) + most_l].tobytes() for s in sets]
            yield pa.record_batch([batch.column("doc_id"), pa.array(map(len, sets), pa.int64()), pa.array(signatures, pa.binary()), pa.array(prefixes, pa.binary())], names=["doc_id", "n", "signature", "prefix"])

    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n long, signature binary, prefix binary")


_BLOCK_SQL = "block long, ids array<long>, sizes array<long>, signatures array<binary>, prefixes array<binary>, keys long"


def _blocks(found: Iterator[tuple], block_keys: int) -> Iterator[pa.RecordBatch]:
    """One task's (node, n, signature, prefix) in blocks of about ``block_keys`` prefix shingles."""
    task, made, rows, held = TaskContext.get().partitionId(), 0, [], 0
    types = (pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.binary()), pa.list_(pa.binary()))

    def flush() -> pa.RecordBatch:
        lists = [pa.array([list(c)], t) for c, t in zip(zip(*rows, strict=True), types, strict=True)]
        return pa.record_batch([pa.array([(task << 24) + made], pa.int64()), *lists, pa.array([held], pa.int64())], names=["block", "ids", "sizes", "signatures", "prefixes", "keys"])

    for row in found:
        rows.append(row)
        held += len(row[3]) // 8
        if held >= block_keys:
            yield flush()
            made, rows, held = made + 1, [], 0
    if rows:
        yield flush()


def _store(blocks: DataFrame, name: str, codec: str) -> DataFrame:
    """Blocks of nodes as a table bucketed by block, so that answers join them where they lie."""
    spark = blocks.sparkSession
    name, parts = f"{name}_{uuid.uuid4().hex}", int(spark.conf.get("spark.sql.shuffle.partitions"))
    blocks.write.bucketBy(max(1, min(parts, 100_000)), "block").sortBy("block").option("compression", codec).option("path", f"{scratch_root(spark)}/{name}").saveAsTable(name)
    atexit.register(_forget, spark, name)
    return spark.table(name)


def node_blocks(nodes: DataFrame, block_keys: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (row for batch in batches for row in zip(*(batch.column(c).to_pylist() for c in ("node", "n", "signature", "prefix")), strict=True))
        yield from _blocks(rows, block_keys)

    return nodes.select("node", "n", "signature", "prefix").mapInArrow(run, _BLOCK_SQL)


class _Block:
    """One block's living nodes: their ids and sizes, the block's distinct keys (sorted) with counts, and each node's postings.

    ``where`` gives every posting's place among the keys; a node's run from ``starts[i]`` to ``starts[i + 1]``.
    """

    def __init__(self, row: dict) -> None:
        rows = list(zip(row["ids"], row["sizes"], row["prefixes"], strict=True))
        if row.get("alive") is not None:
            alive = set(row["alive"])
            rows = [r for r in rows if r[0] in alive]
        self.ids, self.sizes = [r[0] for r in rows], [r[1] for r in rows]
        raw = np.frombuffer(b"".join(r[2] for r in rows), dtype=np.uint64)
        # Mixed again: prefixes hold the smallest hashes, keys should spread over the ranges.
        self.keys, self.where, self.counts = np.unique(mix64(raw) & KEY_BITS, return_inverse=True, return_counts=True)
        self.starts = np.concatenate([[0], np.cumsum([len(r[2]) // 8 for r in rows], dtype=np.int64)])


def _ask(blocks: DataFrame, ranges: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                block = _Block(row)
                keys, counts = block.keys, block.counts
                at = range_bounds(keys, ranges)
                out = [(r, row["block"], int(b - a), pack_sorted(keys[a:b] >> KEY_SHIFT), pack(counts[a:b])) for r, (a, b) in enumerate(zip(at, at[1:], strict=False)) if b > a]
                if out:
                    columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)]
                    yield pa.record_batch(columns, names=["range", "block", "n", "keys", "counts"])

    return blocks.mapInArrow(run, "range int, block long, n long, keys binary, counts binary")


def _answerer(shared_only: bool):
    def answer(table: pa.Table) -> pa.Table:
        """One range's totals, for each block in its own order; 2 stands for any above 1 where only that is asked."""
        rows = sorted(table.to_pylist(), key=lambda r: r["block"])
        keys = np.concatenate([unpack_sorted(r["keys"], r["n"]) for r in rows])
        distinct, where = np.unique(keys, return_inverse=True)
        totals = np.zeros(len(distinct), dtype=np.int64)
        np.add.at(totals, where, np.concatenate([unpack(r["counts"], r["n"]) for r in rows]).astype(np.int64))
        totals = np.minimum(totals, 2) if shared_only else totals
        mine, at, out = totals[where], 0, []
        for r in rows:
            out.append((r["range"], r["block"], r["n"], pack(mine[at : at + r["n"]])))
            at += r["n"]
        columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)]
        return pa.Table.from_arrays(columns, names=["range", "block", "n", "totals"])

    return answer


def choose_prefix(frequency: np.ndarray, n: int, percent: int, most_l: int, costly: int) -> tuple[int, int, np.ndarray] | None:
    """(l, m, posted places) of one document, from its prefix shingles' document frequencies; None if it has no partner.

    Costly shingles (frequency above ``costly``) of an l-prefix are left out, which leaves m = l less their number to
    ask of a partner; m must be at least 1. Of all such l the cheapest is taken, by the postings to be read and the
    candidates to be verified, of which there are fewer the more is asked. Where every prefix has too many costly
    shingles, all of the shortest prefix are posted, and the others of the longest. Shingles that no other set has are never posted.
    """
    base, top = n - needed(n, percent), min(most_l, needed(n, percent))
    if (np.cumsum(frequency > 1)[base:] < np.arange(1, len(frequency) - base + 1)).any():
        return None  # a partner would share l of every l-prefix
    lengths = base + np.arange(1, top + 1)
    heavy = np.cumsum(frequency > costly)[lengths - 1]
    m = np.arange(1, top + 1) - heavy
    read = np.cumsum(np.where((frequency > 1) & (frequency <= costly), frequency, 0))[lengths - 1].astype(float)
    cost = np.where(m >= 1, read * (1.0 + 16.0 / np.maximum(m, 1) ** 2), np.inf)
    best = int(cost.argmin())
    if not np.isfinite(cost[best]):
        light = (frequency[: base + top] > 1) & (frequency[: base + top] <= costly)  # for partners that leave costly ones out
        light[: base + 1] |= frequency[: base + 1] > 1  # for those that post costly ones too
        return top, 1, np.flatnonzero(light)
    part = frequency[: base + best + 1]
    return best + 1, int(m[best]), np.flatnonzero((part > 1) & (part <= costly))


def _informed(blocks: DataFrame, keys_per_range: int, shared_only: bool = False) -> DataFrame:
    """``blocks`` with answers: the document frequency of every key among the living nodes of all blocks, or whether it is above 1."""
    total = int(blocks.agg(F.sum("keys")).first()[0] or 0)
    ranges = max(int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-total // keys_per_range))
    answers = materialise(_ask(blocks, ranges).groupBy("range").applyInArrow(_answerer(shared_only), "range int, block long, n long, totals binary"), "frequencies")
    given = answers.groupBy("block").agg(F.collect_list(F.struct("range", "n", "totals")).alias("answers"))
    return blocks.join(given.hint("merge"), "block")


def _frequencies(row: dict) -> tuple[_Block, np.ndarray]:
    block = _Block(row)
    totals = np.concatenate([unpack(a["totals"], a["n"]) for a in sorted(row["answers"], key=lambda a: a["range"])]).astype(np.int64)
    return block, totals[block.where]


def survivors(blocks: DataFrame, percent: int, keys_per_range: int) -> DataFrame:
    """(block, alive): the nodes of each block that may have a partner, by what they share with any other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                block, frequency = _frequencies(row)
                alive = [node for node, n, a, b in zip(block.ids, block.sizes, block.starts.tolist(), block.starts[1:].tolist(), strict=False) if choose_prefix(frequency[a:b], n, percent, 1, 0) is not None]
                if alive:
                    yield pa.record_batch([pa.array([row["block"]], pa.int64()), pa.array([alive], pa.list_(pa.int64()))], names=["block", "alive"])

    return materialise(_informed(blocks, keys_per_range, True).mapInArrow(run, "block long, alive array<long>"), "alive")


def postings(blocks: DataFrame, percent: int, most_l: int, costly: int, keys_per_range: int) -> DataFrame:
    """(key, node, n, s, l, m, weight): each document's posted shingles, from whole sets.

    ``s`` is the number of its shingles that any other set has; ``weight`` the mean log frequency of its shingles.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                block, frequency = _frequencies(row)
                out: list[list] = [[], [], [], [], [], [], []]
                for i, (node, n, a, b) in enumerate(zip(block.ids, block.sizes, block.starts.tolist(), block.starts[1:].tolist(), strict=False)):
                    chosen = choose_prefix(frequency[a:b], n, percent, most_l, costly)
                    if chosen is not None:
                        l, m, posted = chosen  # noqa: E741
                        k, weight, s = len(posted), float(np.log(frequency[a:b]).mean()), int((frequency[a:b] > 1).sum())
                        for column, values in zip(out, (block.keys[block.where[a:b][posted]].view(np.int64).tolist(), [node] * k, [n] * k, [s] * k, [l] * k, [m] * k, [weight] * k), strict=True):
                            column.extend(values)
                    if len(out[0]) > 50_000 or i + 1 == len(block.ids):
                        columns = [pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.float64()), strict=True)]
                        yield pa.record_batch(columns, names=["key", "node", "n", "s", "l", "m", "weight"])
                        out = [[], [], [], [], [], [], []]

    return materialise(_informed(blocks, keys_per_range).mapInArrow(run, "key long, node long, n long, s long, l int, m int, weight double"), "postings")


def candidate_sets(docs: DataFrame, alive: DataFrame, width: int, block_keys: int, batch_bytes: int = 2 << 20) -> DataFrame:
    """Blocks of the whole sets of the living nodes, from their texts."""
    ids = materialise(alive.select(F.explode("alive").alias("_node")).distinct(), "candidates")
    ids = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids

    def rows_in(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        hashes = _Hashes()
        for batch in slices(batches, "text", batch_bytes):
            for node, found in zip(batch.column("node").to_pylist(), shingle_sets(utf8(batch.column("text")), width, hashes), strict=True):
                yield node, len(found), b"", found.tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:  # one function: two would be two Python workers a task
        yield from _blocks(rows_in(batches), block_keys)

    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("node"), F.col("text").cast("string").alias("text"))
    chosen = rows.join(ids, rows["node"] == ids["_node"], "left_semi")
    return _store(chosen.mapInArrow(run, _BLOCK_SQL), "sets", "uncompressed")


def verify(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (x, y) whose full sets reach the threshold."""
    first = sets.select(F.col("node").alias("x"), F.col("shingles").alias("a"))
    second = sets.select(F.col("node").alias("y"), F.col("shingles").alias("b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for a, b in zip(batch.column("a"), batch.column("b"), strict=True):
                s, t = np.frombuffer(a.as_buffer(), dtype=np.uint64), np.frombuffer(b.as_buffer(), dtype=np.uint64)
                both = len(np.intersect1d(s, t, assume_unique=True))
                keep.append(100 * both >= percent * (len(s) + len(t) - both) and both > 0)
            yield pa.record_batch([batch.column("x").filter(pa.array(keep, pa.bool_())), batch.column("y").filter(pa.array(keep, pa.bool_()))], names=["x", "y"])

    if pairs.count() <= BROADCAST_IDS:  # the sets of x stay where they lie, and only the sets of y that are asked for move
        second = second.join(F.broadcast(pairs.select("y").distinct()), "y", "left_semi")
        pairs = F.broadcast(pairs)
    return first.join(pairs, "x").join(second, "y").select("x", "y", "a", "b").mapInArrow(run, "x long, y long")


def _may_link(n: str, s: str, other_n: str, other_s: str, percent: int):
    """What two sets' sizes allow: they share at most the lesser number of shingles that any other set has."""
    most = F.least(F.col(s), F.col(other_s))
    return (100 * most) >= percent * (F.col(n) + F.col(other_n) - most)


def _asked(pairs: DataFrame) -> DataFrame:
    """Distinct (x, y) of (x, y, lx, mx, ly, my) rows, one a shared posting, that share as many as the shorter prefix asks."""
    ask = F.when(F.col("lx") < F.col("ly"), F.col("mx")).when(F.col("ly") < F.col("lx"), F.col("my")).otherwise(F.greatest("mx", "my"))
    return pairs.groupBy("x", "y").agg(F.count("*").alias("shared"), F.max(ask).alias("asked")).where("shared >= asked").select("x", "y")


def similar_groups(
    docs: DataFrame, width: int = 3, percent: int = 90, most_l: int = 24, costly: int = 32, pivots: int = 2, block_keys: int = 1 << 17, keys_per_range: int = 1 << 18
) -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id (the smallest doc_id reachable by links)."""
    table = materialise(describe(docs, width, percent, most_l), "prefixes")
    nodes = table.where("n > 0").groupBy("signature").agg(F.min(F.struct("doc_id", "n", "prefix")).alias("r")).select("signature", F.col("r.doc_id").alias("node"), F.col("r.n").alias("n"), F.col("r.prefix").alias("prefix"))
    prefixes = _store(node_blocks(nodes, block_keys), "nodes", "zstd")
    named = prefixes.select(F.explode(F.arrays_zip("signatures", "ids")).alias("z")).select(F.col("z.signatures").alias("signature"), F.col("z.ids").alias("node"))
    # Who may have a partner is asked of prefixes first, twice, as what was shared only with those that fell is no longer
    # shared; then of the whole sets of those left, among themselves.
    alive = survivors(prefixes, percent, keys_per_range)
    alive = survivors(prefixes.join(alive.hint("merge"), "block"), percent, keys_per_range)
    stored = candidate_sets(docs, alive, width, block_keys)
    sets = stored.select(F.explode(F.arrays_zip("ids", "prefixes")).alias("z")).select(F.col("z.ids").alias("node"), F.col("z.prefixes").alias("shingles"))
    living = stored.join(survivors(stored, percent, keys_per_range).hint("merge"), "block")
    posted = postings(living, percent, most_l, costly, keys_per_range)

    # Every list against a pivot: first its most typical document, then others by hash, in lists that still hold several components.
    links = None
    lists, tried = posted.withColumn("component", F.col("node")), None
    for turn in range(pivots):
        rank = F.struct("weight", -F.xxhash64("node"), "node", "n", "s", "l", "m", "component") if turn == 0 else F.struct(F.lit(0.0), F.xxhash64(F.lit(turn), "node"), "node", "n", "s", "l", "m", "component")
        heads = lists.groupBy(F.col("key").alias("_key")).agg(F.max(rank).alias("p"), F.min("component").alias("_least"), F.max("component").alias("_most")).where("_least <> _most")
        heads = materialise(heads.select("_key", F.col("p.node").alias("_node"), F.col("p.n").alias("_n"), F.col("p.s").alias("_s"), F.col("p.l").alias("_l"), F.col("p.m").alias("_m"), F.col("p.component").alias("_component")), "pivots")
        met = lists.join(heads.hint("merge"), (lists["key"] == heads["_key"]) & (F.col("component") != F.col("_component")) & _may_link("n", "s", "_n", "_s", percent))
        first = F.col("node") < F.col("_node")
        either = lambda a, b: F.when(first, F.col(a)).otherwise(F.col(b))
        asked = _asked(met.select(either("node", "_node").alias("x"), either("_node", "node").alias("y"), either("l", "_l").alias("lx"), either("m", "_m").alias("mx"), either("_l", "l").alias("ly"), either("_m", "m").alias("my")))
        asked = materialise(asked if tried is None else asked.join(tried, ["x", "y"], "left_anti"), "asked")
        tried = asked if tried is None else materialise(tried.unionByName(asked), "tried")
        found = materialise(verify(asked, sets, percent), "found")
        links = found if links is None else materialise(links.unionByName(found), "found")
        components = connected_components(links)
        lists = _labelled(posted, components)
        mixed = lists.groupBy("key").agg(F.min("component").alias("least"), F.max("component").alias("most")).where("least <> most").select(F.col("key").alias("_key"))
        lists = materialise(lists.join(materialise(mixed, "mixed").hint("merge"), F.col("key") == F.col("_key"), "left_semi"), "lists")

    # What is left: pairs of different components that share enough posted shingles. Each posting brings those of its
    # document's keys, of the lists left, that come before its own, so the join gives a pair at most once: where it
    # shares the last of as many as it must. Shingles of a document that fall together under one key are asked for once.
    own = lists.groupBy(F.col("node").alias("_own")).agg(F.array_sort(F.collect_set("key")).alias("keys"), F.count("*").alias("posted"))
    full = lists.join(own.hint("merge"), lists["node"] == own["_own"]).withColumn("before", F.expr("slice(keys, 1, cast(array_position(keys, key) as int) - 1)"))
    full = full.withColumn("m", F.greatest(F.lit(1), F.col("m") - (F.col("posted") - F.size("keys"))).cast("int"))
    full = materialise(full.drop("_own", "weight", "keys", "posted"), "keyed")
    side = lambda mark: full.select(*[F.col(c).alias(f"{c}{mark}") for c in ("key", "node", "n", "s", "l", "m", "component", "before")])
    a, b = side("1"), side("2")
    ask = F.when(F.col("l1") < F.col("l2"), F.col("m1")).when(F.col("l2") < F.col("l1"), F.col("m2")).otherwise(F.greatest("m1", "m2"))
    apart = (F.col("key1") == F.col("key2")) & (F.col("node1") < F.col("node2")) & (F.col("component1") != F.col("component2"))
    met = a.join(b.hint("merge"), apart & _may_link("n1", "s1", "n2", "s2", percent) & (F.size(F.array_intersect("before1", "before2")) + 1 == ask))
    pairs = met.select(F.col("node1").alias("x"), F.col("node2").alias("y")).distinct()
    pairs = materialise(pairs.join(tried, ["x", "y"], "left_anti"), "pairs")
    found = materialise(verify(pairs, sets, percent), "found")
    components = connected_components(links.unionByName(found))

    grouped = materialise(_labelled(named, components).select(F.col("signature").alias("_signature"), "component"), "components")
    rows = table.select("doc_id", "n", "signature").join(grouped.hint("merge"), (F.col("signature") == F.col("_signature")) & (F.col("n") > 0), "left")
    shown = lambda c: F.nullif(c, F.lit(NO_ID))
    return rows.select(shown(F.col("doc_id")).alias("doc_id"), F.col("n").alias("n_shingles"), shown(F.coalesce("component", "doc_id")).alias("component_id"))


def _labelled(rows: DataFrame, components: DataFrame) -> DataFrame:
    of = components.select(F.col("node").alias("_of"), F.col("component").alias("_label"))
    return rows.drop("component").join(of, rows["node"] == of["_of"], "left").withColumn("component", F.coalesce("_label", "node")).drop("_of", "_label")


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with one document of each group of linked ones: the smallest id, with all its columns, whatever their names."""
    groups = similar_groups(docs, **options).where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select("doc_id").distinct()
    kept = groups.select(F.col("doc_id").alias("kept"))
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("id"))
    return rows.join(kept, F.col("id").eqNullSafe(F.col("kept")), "left_semi").select("row.*")
