"""Removal of repeated passages by suffix sorting, deep-shallow.

A byte goes if a string of ``length`` bytes that covers it also starts in a document with a smaller id. Only
suffixes that may repeat are sorted: every string of that length holds one canonical anchor, the leftmost least hash
among its short grams, so equal strings have equal anchors at equal places. Anchors that only one document has are
ruled out by counting; for the others the strings around the anchor meet in one task, whose suffixes are sorted by
multikey quicksort on machine words to a shallow depth, and from there by blind tries. Equal neighbours give the
least document of each string.

Documents are kept in blocks, stored bucketed by block. Blocks first settle what repeats inside them, and send each
anchor's distinct surroundings once, so a passage that a third of all documents share is one string a block.

Defined results: a null text counts as empty; a copy of a whole text of at least ``length`` bytes goes wholly unless
its id is the least; rows repeated with the same id do not remove each other; null ids count as the smallest; an
empty table gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import atexit
import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from numpy.lib.stride_tricks import sliding_window_view
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blobs import mix64, pack, pack_sorted, range_bounds, unpack, unpack_sorted
from .common import materialise, rows_of, scratch_root, slices, utf8
from .interpolation import _forget

NO_ID = -(1 << 63)
#: Positions hashed at once.
TILE = 1 << 18


# ---- deep-shallow sorting -------------------------------------------------------------------------------------


class BlindTrie:
    """Orders strings that agree up to some depth, looking at one branching byte a node and comparing once."""

    __slots__ = ("root", "text", "limit")

    def __init__(self, text: bytes, limit: int | None = None) -> None:
        self.text, self.limit, self.root = text, limit, None

    def _suffix(self, at: int, skip: int) -> bytes:
        return self.text[at + skip : at + self.limit if self.limit else None]

    def sort(self, starts: list[int], depth: int) -> list[list[int]]:
        """Classes of equal strings, in order. A node is [depth, {byte: child}], a leaf a list of starts."""
        root: list | None = None
        for at in starts:
            own = self._suffix(at, depth)
            if root is None:
                root = ["leaf", [at]]
                continue
            node, path = root, []
            while node[0] != "leaf":  # blindly down to some leaf
                path.append(node)
                key = own[node[0]] if node[0] < len(own) else -1
                node = node[1].get(key) or next(iter(node[1].values()))
            other = self._suffix(node[1][0], depth)
            if own == other:
                node[1].append(at)
                continue
            common, low, high = 0, 0, min(len(own), len(other))
            while low < high:  # bisect for the first difference
                common = (low + high + 1) // 2
                if own[:common] == other[:common]:
                    low = common
                else:
                    high = common - 1
            common = low
            above, below = None, root
            while below[0] != "leaf" and below[0] < common:
                above, below = below, below[1][own[below[0]] if below[0] < len(own) else -1]
            mine = own[common] if common < len(own) else -1
            if below[0] == common and below[0] != "leaf":
                below[1][mine] = ["leaf", [at]]
                continue
            split = [common, {mine: ["leaf", [at]], (other[common] if common < len(other) else -1): below}]
            if above is None:
                root = split
            else:
                above[1][own[above[0]] if above[0] < len(own) else -1] = split
        out: list[list[int]] = []
        stack = [root] if root else []
        while stack:
            node = stack.pop()
            if node[0] == "leaf":
                out.append(node[1])
            else:
                stack.extend(node[1][k] for k in sorted(node[1], reverse=True))
        return out


def _words(text: np.ndarray, starts: np.ndarray, skip: int | np.ndarray) -> np.ndarray:
    """Eight bytes after ``skip`` as one big-endian number; ``text`` must be padded."""
    eight = sliding_window_view(text, 8)[starts + skip]
    return np.ascontiguousarray(eight).view(">u8").reshape(-1).astype(np.uint64)


def multikey_quicksort(text: np.ndarray, starts: np.ndarray, depth: int, group: np.ndarray | None = None, stats: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(order of ``starts``, where each group begins): strings of a group agree on their first ``depth`` bytes, or are alone.

    Every unresolved group is partitioned in three about a pivot word of eight bytes, the median of three of its own:
    less and greater stay at their depth, equal goes eight bytes deeper. Groups of one, and those at ``depth``, are done
    and not looked at again. All groups of a round are partitioned at once, each element moved once. ``group`` tells
    strings apart beforehand: only those of one group are compared. ``stats`` counts rounds, groups split and elements.
    """
    stats = {} if stats is None else stats
    order = np.arange(len(starts)) if group is None else np.argsort(group, kind="stable")
    if not len(order):
        return order, np.zeros(0, dtype=np.int64)
    begin = np.zeros(1, dtype=np.int64) if group is None else np.flatnonzero(np.diff(group[order], prepend=group[order[0]] - 1))
    size = np.diff(np.append(begin, len(order)))
    deep, done = np.zeros(len(begin), dtype=np.int64), []
    while True:
        over = (size <= 1) | (deep >= depth)
        done.append(begin[over])
        begin, size, deep = begin[~over], size[~over], deep[~over]
        if not len(begin):
            break
        first = np.cumsum(size) - size
        of = np.repeat(np.arange(len(begin)), size)
        places = np.arange(len(of)) + (begin - first)[of]
        members = order[places]
        word = _words(text, starts[members], deep[of])
        pivot = np.sort(np.stack([word[first], word[first + size // 2], word[first + size - 1]]), axis=0)[1][of]
        side = (word >= pivot).astype(np.int64) + (word > pivot)
        slot = of * 3 + side
        counts = np.bincount(slot, minlength=3 * len(begin))
        ahead = np.cumsum(counts) - counts
        for k in range(3):
            mine = np.flatnonzero(side == k)
            own = counts[k::3]
            order[begin[of[mine]] - first[of[mine]] + ahead[slot[mine]] + np.arange(len(mine)) - (np.cumsum(own) - own)[of[mine]]] = members[mine]
        stats["rounds"] = stats.get("rounds", 0) + 1
        stats["split"] = stats.get("split", 0) + len(begin)
        stats["moved"] = stats.get("moved", 0) + len(of)
        use = counts > 0
        which = np.repeat(np.arange(len(begin)), 3)[use]
        size, deep = counts[use], (deep[which] + 8 * (np.arange(len(counts)) % 3 == 1)[use])
        begin = (begin - first)[which] + ahead[use]
    return order, np.sort(np.concatenate(done))


def deep_shallow(text: np.ndarray, starts: np.ndarray, length: int, shallow: int = 40, group: np.ndarray | None = None, stats: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sort the strings text[s : s + length]: (order of ``starts``, class of each in that order; equal strings share one).

    Multikey quicksort down to ``shallow`` bytes; a group that is still together there and not all equal is finished by
    a blind trie. Where ``group`` tells strings apart beforehand, the order is by group first.
    """
    shallow = min(shallow, length) // 8 * 8
    stats = {} if stats is None else stats
    order, begins = multikey_quicksort(text, starts, shallow, group, stats)
    if not len(order):
        return order, np.zeros(0, dtype=np.int64)
    group = np.zeros(len(order), dtype=np.int64)
    group[begins] = 1
    group = np.cumsum(group) - 1
    edges = np.append(begins, len(order))
    tails = sliding_window_view(text, length - shallow)[starts[order] + shallow] if shallow < length else np.zeros((len(order), 0), dtype=np.uint8)
    same = np.ones(len(order), dtype=bool)
    same[1:] = (tails[1:] == tails[:-1]).all(axis=1) | (group[1:] != group[:-1])
    ragged = np.unique(group[~same])
    stats["blind"] = stats.get("blind", 0) + len(ragged)
    label = group * 1.0
    raw = text.tobytes() if len(ragged) else b""
    trie = BlindTrie(raw, length)
    for g in ragged.tolist():
        a, b = int(edges[g]), int(edges[g + 1])
        back: dict[int, list[int]] = {}
        for i in order[a:b].tolist():
            back.setdefault(int(starts[i]), []).append(i)
        classes = trie.sort(sorted(back), shallow)
        flat = [(i, k) for k, c in enumerate(classes) for s in c for i in back[s]]
        order[a:b] = [i for i, _ in flat]
        label[a:b] = [g + k / len(classes) for _, k in flat]
    return order, np.cumsum(np.diff(label, prepend=-1.0) != 0) - 1


def suffix_array(text: bytes, shallow: int = 16) -> list[int]:
    """The whole suffix array of one text: words to the shallow depth, blind tries below it.

    The padding that words read past the end sorts a short suffix with those it begins; the tries put it first.
    """
    padded = np.frombuffer(text + bytes(shallow + 8), dtype=np.uint8)
    starts = np.arange(len(text))
    order, group = deep_shallow(padded, starts, shallow, shallow)
    out: list[int] = []
    edges = np.append(np.flatnonzero(np.diff(group, prepend=-1)), len(order)) if len(order) else np.zeros(1, dtype=int)
    trie = BlindTrie(text)
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        members = sorted(order[a:b].tolist())
        out.extend(members if len(members) == 1 else [s for c in trie.sort(members, 0) for s in c])
    return out


# ---- anchors --------------------------------------------------------------------------------------------------


def _gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """A 64-bit hash of the ``gram`` bytes from every position on, by doubling."""
    base = np.uint64(0x9E3779B97F4A7C15)
    span, h, power = 1, data.astype(np.uint64) + np.uint64(1), base
    done, out = 0, None
    while True:
        if gram & span:
            out = h.copy() if out is None else out[: len(h) - done] * power + h[done : done + len(out)][: len(h) - done]
            done += span
        if done == gram:
            return mix64(out[: len(data) - gram + 1])
        h = h[: len(h) - span] * power + h[span:]
        power = power * power
        span *= 2


def _leftmost_least(h: np.ndarray, width: int) -> np.ndarray:
    """Position of the leftmost least value of every window of ``width``, by doubling."""
    at, span = np.arange(len(h), dtype=np.int32), 1
    while span * 2 <= width:
        at, span = _better(h, at, span), span * 2
    return _better(h, at, width - span) if span < width else at


def _better(h: np.ndarray, at: np.ndarray, shift: int) -> np.ndarray:
    left, right = at[: len(at) - shift], at[shift:]
    return np.where(h[right] < h[left], right, left)


def anchor_runs(data: np.ndarray, ends: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of string starts with one anchor: (document, first start, last start, key); starts are places in ``data``.

    ``data`` holds documents end to end; a string never crosses a document's end.
    """
    out: list[tuple] = []
    for tile in range(0, max(0, len(data) - length + 1), TILE):
        part = data[tile : tile + TILE + length - 1]
        h = _gram_hashes(part, gram)
        anchor = _leftmost_least(h, length - gram + 1)
        first = np.searchsorted(ends, tile, side="right")
        place = np.arange(tile, tile + len(anchor))
        doc = first + np.searchsorted(ends[first:], place, side="right")
        ok = place + length <= ends[np.minimum(doc, len(ends) - 1)]
        new = np.ones(len(anchor), dtype=bool)
        new[1:] = (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1]) | (ok[1:] != ok[:-1])
        at = np.flatnonzero(new)
        stop = np.append(at[1:], len(anchor)) - 1
        use = ok[at]
        out.append((doc[at][use], tile + at[use], tile + stop[use], mix64(h[anchor[at]][use])))  # least hashes are small: mixed again, keys spread
    if not out:
        return (np.zeros(0, dtype=np.int64),) * 3 + (np.zeros(0, dtype=np.uint64),)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


# ---- blocks ---------------------------------------------------------------------------------------------------


def block_table(docs: DataFrame, block_bytes: int) -> DataFrame:
    """Documents in blocks: ids, ends of their texts, text digests, and the texts end to end (compressed)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, made, ids, texts, held = TaskContext.get().partitionId(), 0, [], [], 0
        names = ["block", "ids", "ends", "digests", "texts"]

        def flush() -> pa.RecordBatch:
            ends = np.cumsum([len(t) for t in texts])
            row = ([(task << 24) + made], [ids], [ends.tolist()], [[hashlib.sha256(t).digest() for t in texts]], [zstandard.ZstdCompressor(3).compress(b"".join(texts))])
            types = (pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.binary()), pa.binary())
            return pa.record_batch([pa.array(c, t) for c, t in zip(row, types, strict=True)], names=names)

        for batch in slices(batches, "text", 1 << 20):
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), utf8(batch.column("text")), strict=True):
                ids.append(doc_id)
                texts.append(text)
                held += len(text) + 64
                if held >= block_bytes:
                    yield flush()
                    made, ids, texts, held = made + 1, [], [], 0
        if ids:
            yield flush()

    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "block long, ids array<long>, ends array<long>, digests array<binary>, texts binary")


class _Texts:
    """The documents of one block; ``active`` are those with the least id among equal texts."""

    def __init__(self, row: dict) -> None:
        self.ids, self.ends = np.array(row["ids"], dtype=np.int64), np.array(row["ends"], dtype=np.int64)
        self.begins = np.concatenate([[0], self.ends[:-1]])
        self.raw = zstandard.ZstdDecompressor().decompress(row["texts"]) if len(self.ends) and self.ends[-1] else b""
        self.data = np.frombuffer(self.raw, dtype=np.uint8)
        first = np.full(len(self.ids), NO_ID, dtype=np.int64)
        for o in row["owners"]:
            first[o["at"]] = o["owner"]
        self.active = self.ids == first

    def runs(self, length: int, gram: int):
        doc, a, b, key = anchor_runs(self.data, self.ends, length, gram)
        use = self.active[doc]
        return doc[use], a[use], b[use], key[use]


def _ask(blocks: DataFrame, ranges: int, length: int, gram: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                doc, _, _, key = _Texts(row).runs(length, gram)
                keys, count = _documents_per_key(doc, key)
                at = range_bounds(keys, ranges)
                out = [(r, row["block"], int(b - a), pack_sorted(keys[a:b]), pack(count[a:b])) for r, (a, b) in enumerate(zip(at, at[1:], strict=False)) if b > a]
                if out:
                    columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)]
                    yield pa.record_batch(columns, names=["range", "block", "n", "keys", "counts"])

    return blocks.mapInArrow(run, "range int, block long, n long, keys binary, counts binary")


def _documents_per_key(doc: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((doc, key))
    k, d = key[order], doc[order]
    new = np.ones(len(k), dtype=bool)
    new[1:] = (k[1:] != k[:-1]) | (d[1:] != d[:-1])
    return np.unique(k[new], return_counts=True)


def _shared(table: pa.Table) -> pa.Table:
    """One range's answers: for each block, which of its keys (in its order) two or more documents have."""
    rows = sorted(table.to_pylist(), key=lambda r: r["block"])
    keys = np.concatenate([unpack_sorted(r["keys"], r["n"]) for r in rows])
    distinct, where = np.unique(keys, return_inverse=True)
    totals = np.zeros(len(distinct), dtype=np.int64)
    np.add.at(totals, where, np.concatenate([unpack(r["counts"], r["n"]) for r in rows]).astype(np.int64))
    mine, at, out = totals[where] > 1, 0, []
    for r in rows:
        out.append((r["range"], r["block"], r["n"], np.packbits(mine[at : at + r["n"]]).tobytes()))
        at += r["n"]
    columns = [pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)]
    return pa.Table.from_arrays(columns, names=["range", "block", "n", "bits"])


_SENT = "range int, block long, n long, keys binary, ids binary, docs binary, firsts binary, spans binary, texts binary"


def _send(blocks: DataFrame, ranges: int, length: int, gram: int) -> DataFrame:
    """The distinct surroundings of shared anchors, by range; and what the block settles itself, as range -1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                texts = _Texts(row)
                doc, a, b, key = texts.runs(length, gram)
                keys = np.unique(key)
                answers = sorted(row["answers"] or [], key=lambda x: x["range"])
                bits = np.concatenate([np.unpackbits(np.frombuffer(x["bits"], dtype=np.uint8), count=x["n"]) for x in answers]).astype(bool) if answers else np.zeros(0, dtype=bool)
                use = np.flatnonzero(bits[np.searchsorted(keys, key)]) if len(key) else np.zeros(0, dtype=np.int64)
                least: dict[tuple[int, bytes], int] = {}
                raw, kept, covered = texts.raw, [], []
                for i, k, s, e in zip(use.tolist(), key[use].tolist(), a[use].tolist(), (b[use] + length).tolist(), strict=True):
                    at = (k, raw[s:e])
                    j = least.setdefault(at, i)
                    if j != i:
                        mine, other = texts.ids[doc[i]], texts.ids[doc[j]]
                        if mine < other:
                            least[at] = i
                            covered.append(j)
                        elif mine > other:
                            covered.append(i)
                        else:
                            kept.append(i)  # the same document: both may be covered from elsewhere
                kept = np.array(sorted({*least.values(), *kept}), dtype=np.int64)
                out = []
                if covered:
                    c = np.array(covered)
                    out.append(_packed(-1, row["block"], texts, c, doc, a, b, key, length, False))
                if len(kept):
                    kept = kept[np.argsort(key[kept], kind="stable")]
                    at = range_bounds(key[kept], ranges)
                    out.extend(_packed(r, row["block"], texts, kept[x:y], doc, a, b, key, length, True) for r, (x, y) in enumerate(zip(at, at[1:], strict=False)) if y > x)
                if out:
                    types = (pa.int32(), pa.int64(), pa.int64(), *[pa.binary()] * 6)
                    yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=["range", "block", "n", "keys", "ids", "docs", "firsts", "spans", "texts"])

    return blocks.mapInArrow(run, _SENT)


def _packed(r: int, block: int, texts: _Texts, at: np.ndarray, doc, a, b, key, length: int, with_texts: bool) -> tuple:
    joined = b"".join(texts.raw[s : e + length] for s, e in zip(a[at].tolist(), b[at].tolist(), strict=True)) if with_texts else b""
    return (
        r,
        block,
        len(at),
        pack_sorted(key[at]) if with_texts else b"",
        pack((texts.ids[doc[at]] - NO_ID).astype(np.uint64)) if with_texts else b"",
        pack(doc[at].astype(np.uint64)),
        pack((a[at] - texts.begins[doc[at]]).astype(np.uint64)),
        pack((b[at] - a[at]).astype(np.uint64)),
        zstandard.ZstdCompressor(1).compress(joined) if with_texts else b"",
    )


def _resolver(length: int):
    def resolve(table: pa.Table) -> pa.Table:
        """Covered runs of starts of one range's strings, for each block: (document, first start, span)."""
        rows = sorted(table.to_pylist(), key=lambda r: r["block"])
        key = np.concatenate([unpack_sorted(r["keys"], r["n"]) for r in rows])
        ids = np.concatenate([unpack(r["ids"], r["n"]) for r in rows])
        doc = np.concatenate([unpack(r["docs"], r["n"]) for r in rows]).astype(np.int64)
        first = np.concatenate([unpack(r["firsts"], r["n"]) for r in rows]).astype(np.int64)
        span = np.concatenate([unpack(r["spans"], r["n"]) for r in rows]).astype(np.int64)
        owner = np.repeat(np.arange(len(rows)), [r["n"] for r in rows])
        raw = b"".join(zstandard.ZstdDecompressor().decompress(r["texts"]) for r in rows)
        stop = np.cumsum(span + length)
        start = stop - span - length

        # Equal surroundings are settled as wholes; groups of one anchor with one surrounding need no sorting.
        number: dict[tuple[int, bytes], int] = {}
        which = np.fromiter((number.setdefault((k, raw[s:e]), len(number)) for k, s, e in zip(key.tolist(), start.tolist(), stop.tolist(), strict=True)), dtype=np.int64, count=len(key))
        least = np.full(len(number), np.iinfo(np.uint64).max, dtype=np.uint64)
        np.minimum.at(least, which, ids)
        covered_whole = ids > least[which]
        sample = np.full(len(number), -1, dtype=np.int64)
        sample[which[::-1]] = np.arange(len(key))[::-1]
        _, group, size = np.unique(key[sample], return_inverse=True, return_counts=True)
        several = np.flatnonzero(size[group] > 1)

        hit: dict[int, np.ndarray] = {}
        if len(several):
            rep = sample[several]
            counts = span[rep] + 1
            string = np.repeat(several, counts)
            offset = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
            at = np.repeat(start[rep], counts) + offset
            text = np.frombuffer(raw + bytes(length + 8), dtype=np.uint8)
            order, label = deep_shallow(text, at, length, group=np.repeat(group[several], counts))  # equal strings have one anchor
            by = np.full(int(label.max()) + 1, np.iinfo(np.uint64).max, dtype=np.uint64)
            np.minimum.at(by, label, least[string[order]])
            floor = np.empty(len(at), dtype=np.uint64)
            floor[order] = by[label]
            edges = np.cumsum(counts)
            lowered = np.flatnonzero(floor < least[string])
            for s in np.unique(string[lowered]).tolist():
                i = int(np.searchsorted(several, s))
                hit[s] = floor[edges[i] - counts[i] : edges[i]]

        out = []
        for i, r in enumerate(rows):
            mine = np.flatnonzero(owner == i)
            done = mine[covered_whole[mine]]
            parts = [(doc[done], first[done], span[done])]
            for j in mine[~covered_whole[mine]].tolist():
                floors = hit.get(int(which[j]))
                if floors is not None:
                    edge = np.flatnonzero(np.diff(np.concatenate([[0], (floors < ids[j]).astype(np.int8), [0]])))
                    a, b = edge[::2], edge[1::2]
                    parts.append((np.full(len(a), doc[j]), first[j] + a, b - a - 1))
            d, f, s = (np.concatenate(c) for c in zip(*parts, strict=True))
            if len(d):
                out.append((r["block"], len(d), pack(d.astype(np.uint64)), pack(f.astype(np.uint64)), pack(s.astype(np.uint64))))
        types = (pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 5, types, strict=True)], names=["block", "n", "docs", "firsts", "spans"])

    return resolve


def remove_repeats(docs: DataFrame, length: int = 50, gram: int = 20, block_bytes: int = 3 << 20, anchors_per_range: int = 1 << 18, with_spans: bool = False) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256; with ``with_spans`` also spans, the removed [begin, end)."""
    if not 0 < gram < length:
        raise ValueError("the gram must be shorter than the repeated string")
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    name = f"texts_{uuid.uuid4().hex}"
    block_table(docs, block_bytes).write.bucketBy(max(1, min(parts, 100_000)), "block").sortBy("block").option("compression", "uncompressed").option("path", f"{scratch_root(spark)}/{name}").saveAsTable(name)
    atexit.register(_forget, spark, name)
    stored = spark.table(name)

    # Of equal texts only the one with the least id takes part; the others are settled by it.
    each = stored.select("block", F.posexplode(F.arrays_zip("ids", "digests")).alias("at", "d")).select("block", "at", F.col("d.ids").alias("id"), F.col("d.digests").alias("digest"))
    each = materialise(each, "digests")
    least = materialise(each.groupBy(F.col("digest").alias("_digest")).agg(F.min("id").alias("owner")), "owners")
    owned = each.join(least, each["digest"] == least["_digest"]).groupBy("block").agg(F.collect_list(F.struct("at", "owner")).alias("owners"))
    owned = materialise(owned, "owned")
    blocks = stored.join(owned.hint("merge"), "block")

    total = int(stored.agg(F.sum(F.element_at("ends", -1))).first()[0] or 0)
    ranges = max(parts, -(-2 * total // ((length - gram + 2) * anchors_per_range)))
    shared = materialise(_ask(blocks, ranges, length, gram).groupBy("range").applyInArrow(_shared, "range int, block long, n long, bits binary"), "shared")
    given = shared.groupBy("block").agg(F.collect_list(F.struct("range", "n", "bits")).alias("answers"))
    sent = materialise(_send(blocks.join(given.hint("merge"), "block", "left"), ranges, length, gram), "surroundings", codec="uncompressed")
    found = sent.where("range >= 0").groupBy("range").applyInArrow(_resolver(length), "block long, n long, docs binary, firsts binary, spans binary")
    found = found.unionByName(sent.where("range < 0").select("block", "n", "docs", "firsts", "spans"))
    covered = materialise(found, "covered").groupBy("block").agg(F.collect_list(F.struct("n", "docs", "firsts", "spans")).alias("covered"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of(batch):
                texts = _Texts(row)
                change = np.zeros(len(texts.data) + 1, dtype=np.int32)
                for c in row["covered"] or []:
                    d, f, s = (unpack(c[k], c["n"]).astype(np.int64) for k in ("docs", "firsts", "spans"))
                    begin = texts.begins[d] + f
                    np.add.at(change, begin, 1)
                    np.add.at(change, begin + s + length, -1)
                gone = np.cumsum(change[:-1]) > 0
                out = []
                for i, (a, b) in enumerate(zip(texts.begins.tolist(), texts.ends.tolist(), strict=True)):
                    mine = gone[a:b] if texts.active[i] or b - a < length else np.ones(b - a, dtype=bool)
                    edge = np.flatnonzero(np.diff(np.concatenate([[False], mine, [False]]).astype(np.int8)))
                    kept = texts.data[a:b][~mine].tobytes() if len(edge) else texts.raw[a:b]
                    doc_id = int(texts.ids[i])
                    out.append((None if doc_id == NO_ID else doc_id, b - a, int(mine.sum()), len(edge) // 2, hashlib.sha256(kept).hexdigest(), [{"begin": x, "end": y} for x, y in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True)] if with_spans else None))
                types = (*[pa.int64()] * 4, pa.string(), pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())])))
                yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"])

    result = blocks.join(covered.hint("merge"), "block", "left").mapInArrow(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<begin:long,end:long>>")
    return result if with_spans else result.drop("spans")
