"""Every corpus operator against a brute-force version, on awkward rows and on the smallest test table."""

import hashlib
import math
import random
import zlib
from array import array
from collections import Counter, defaultdict

import numpy as np
import pytest

from gapweave.llm import chunking, components, exact_dedup, interpolation, jaccard_join, language_id, media, mixing, pieces, suffix_dedup, token_counts, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size int, component string, _size int, block string"
PASSAGE = "the quick brown fox jumps over the lazy dog and then walks home slowly in the rain "


def awkward_rows():
    """Nulls, empty and long texts, ties, repeated rows, shared passages, near copies; columns with clashing names."""
    r = random.Random(3)
    words = [f"w{i}" for i in range(400)]
    rows = [(1, None), (2, ""), (3, "   \n\t "), (4, "Hello"), (5, "hello"), (6, "one two"), (7, "One Two"), (8, "é ß 世界 😀 ▁x"), (9, "...!!! 123")]
    base = " ".join(r.choice(words) for _ in range(300))
    rows += [(10, base), (11, base), (11, base), (12, base.upper())]
    for k in range(13, 25):  # near copies: a word or two changed
        near = base.split()
        for _ in range(k % 4 + 1):
            near[r.randrange(len(near))] = f"new{r.randrange(1000)}"
        rows.append((k, " ".join(near)))
    for k in range(25, 45):
        own = [" ".join(r.choice(words) for _ in range(r.randint(1, 120)))]
        if k % 2:
            own.insert(r.randint(0, 1), PASSAGE * (k % 3 + 1))
        rows.append((k, " ".join(own)))
    rows.append((45, " ".join(r.choice(words) for _ in range(30_000))))
    rows.append((46, "ab" * 200))
    rows.append((47, "ab" * 150))
    return [(i, t, ("en", "de", None)[k % 3], (None, "a", "b", "z")[k % 4], None, k, "c", 1, "b") for k, (i, t) in enumerate(rows)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward_rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def plain():
    return [(r[0], r[1]) for r in awkward_rows()]


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def low(text):
    return (text or "").encode().lower()


# ---- 1 mixing -------------------------------------------------------------------------------------------------


def test_water_fill_reaches_the_fixed_point():
    t = mixing.water_fill([100, 10, 50, 0], [3, 1, 2, 3], 240, 2)
    assert t == pytest.approx([132.0, 20.0, 88.0, 0.0])
    assert all(x <= 2 * s + 1e-9 for x, s in zip(t, [100, 10, 50, 0]))
    free = [x / w for x, w, s in zip(t, [3, 1, 2], [100, 10, 50]) if x < 2 * s - 1e-9]
    assert max(free, default=0) - min(free, default=0) < 1e-9
    assert sum(mixing.water_fill([1, 1], [1, 1], 100, 2)) == 4


@pytest.mark.xfail(strict=True, reason="written when a fractional repetition cut texts; now only whole documents are taken, and no choice of them comes this near in source a (README)")
def test_mix_meets_targets_and_repeats(docs, plain):
    rows = mixing.mix(docs).collect()
    assert Counter(map(tuple, rows)) == Counter(map(tuple, mixing.mix(docs.repartition(7)).collect()))
    assert Counter((r.doc_id, r["size"]) for r in rows) == Counter((i, len(low(t).split())) for i, t in plain)
    taken, target = defaultdict(int), {}
    for r in rows:
        taken[r.source] += r.taken
        target[r.source] = r.target
        assert 0 <= r.taken <= 2 * r["size"]
    longest = max(r["size"] for r in rows)
    assert all(abs(taken[s] - target[s]) <= max(2, 0.01 * longest) for s in target)
    assert sum(target.values()) == pytest.approx(1.5 * sum(len(low(t).split()) for _, t in plain))


def test_mix_rows_repeat_as_the_mix_says(docs, empty):
    want = sum(r.taken for r in mixing.mix(docs).collect())
    out = mixing.mix_rows(docs)
    assert out.columns == docs.columns
    assert sum(len(low(r.text).split()) for r in out.collect()) == want
    assert mixing.mix(empty).count() == 0 and mixing.mix_rows(empty).count() == 0


def test_mix_repeats_agree_and_miss_by_less_than_a_document(docs, plain):
    rows = mixing.mix(docs).collect()
    assert Counter(map(tuple, rows)) == Counter(map(tuple, mixing.mix(docs.repartition(7)).collect()))
    assert Counter((r.doc_id, r["size"]) for r in rows) == Counter((i, len(low(t).split())) for i, t in plain)
    for s in {r.source for r in rows}:
        mine = [r for r in rows if r.source == s]
        assert abs(sum(r.taken for r in mine) - mine[0].target) <= max(r["size"] for r in mine)
    assert all(0 <= r.taken <= 2 * r["size"] for r in rows)
    assert sum({r.source: r.target for r in rows}.values()) == pytest.approx(1.5 * sum(len(low(t).split()) for _, t in plain))


def test_mix_rows_keep_whole_texts(spark):
    """No row is a prefix, also where a source's target is below its size; each target is missed by less than a document."""
    r = random.Random(7)
    rows = [(i, "\n".join(f"w{r.randrange(50)}" for _ in range(r.randint(1, 40))) + " ", "big" if i % 20 else "small") for i in range(400)]
    rows += [(400, "one\ttwo  three", None), (400, "one\ttwo  three", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    for buckets in (1, 7, 4096):
        plan = mixing.mix(docs, (1, 5, 2), 0.4, 2.0, buckets=buckets).collect()
        out = Counter((o.doc_id, o.text) for o in mixing.mix_rows(docs, (1, 5, 2), 0.4, 2.0, buckets=buckets).collect())
        assert set(out) <= {(i, t) for i, t, _ in rows}
        assert sum(out.values()) == sum(p.repeats for p in plan) and {p.doc_id: p.repeats for p in plan if p.repeats} == {i: n // (2 if i == 400 else 1) for (i, _), n in out.items()}
        for source in ("big", "small"):
            mine = [p for p in plan if p.source == source]
            assert abs(sum(p.taken for p in mine) - mine[0].target) < max(p["size"] for p in mine)


# ---- 2 media --------------------------------------------------------------------------------------------------


def test_chunks_rebuild_and_survive_insertions():
    r = np.random.default_rng(1)
    text = r.integers(97, 123, 60_000, dtype=np.uint8).tobytes()
    c = chunking.Chunker(least=256, bits=9, most=4096)
    a, b = c.cut([text])[0], c.cut([b"inserted" + text])[0]
    assert b"".join(a) == text and all(len(x) <= 4096 for x in a) and all(len(x) >= 256 for x in a[:-1])
    assert len(set(a) & set(b)) > 0.8 * len(a)
    assert c.cut([b"x", text])[1] == a  # cuts do not depend on the batch
    assert c.cut([b""]) == [[b""]]


def test_the_store_holds_the_media_files(docs, plain):
    """Chunks, put in the manifest's order, are the WAV files themselves, header included."""
    c = chunking.Chunker(least=64, bits=6, most=512)
    store = {(bytes(r.digest), r.salt): media._open(bytes(r.data)) for r in media.chunk_store(docs, c).collect()}
    got = Counter()
    for r in media.manifests(docs, c).collect():
        got[(r.doc_id, b"".join(store[bytes(d), media._salt(bytes(r.media_sha256))] for d in r.chunks))] += 1
    assert got == Counter((i, media.to_media(media.payload_of((t or "").encode()))) for i, t in plain)
    assert all(m.startswith(b"RIFF") for _, m in got)


def test_media_round_trip(docs, plain, empty):
    rows = media.media_features(docs, chunking.Chunker(least=64, bits=6, most=512)).collect()
    assert len(rows) == len(plain)
    want = Counter()
    for i, t in plain:
        p = media.payload_of((t or "").encode())
        m = media.to_media(p)
        want[(i, len((t or "").encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]), len(m), hashlib.sha256(m).hexdigest(), media.feature_of(p))] += 1
    assert Counter(map(tuple, rows)) == want
    assert media.media_features(empty).count() == 0


# ---- 3 suffix-array dedup -------------------------------------------------------------------------------------


@pytest.mark.parametrize("seed", range(6))
def test_suffix_array(seed):
    r = random.Random(seed)
    for text in (bytes(r.choice(b"ab") for _ in range(r.randint(0, 80))), bytes(r.choice(b"abc") for _ in range(7)) * 12, b"a" * 50):
        assert suffix_dedup.suffix_array(text) == sorted(range(len(text)), key=lambda i: text[i:])


def test_deep_shallow_orders_equal_prefixes():
    r = random.Random(9)
    stems = [bytes(r.choice(b"xy") for _ in range(44)) for _ in range(3)]
    text = b"".join(r.choice(stems) + bytes(r.choice(b"pq") for _ in range(6)) for _ in range(60))
    padded = np.frombuffer(text + bytes(64), dtype=np.uint8)
    starts = np.arange(0, len(text), 50)
    order, label = suffix_dedup.deep_shallow(padded, starts, 50)
    strings = [text[starts[i] : starts[i] + 50] for i in order]
    assert strings == sorted(strings)
    assert all((a == b) == (x == y) for a, b, x, y in zip(strings, strings[1:], label, label[1:]))


def test_multikey_quicksort_partitions_only_what_is_unresolved():
    r = random.Random(2)
    stems = [bytes(r.choice(b"abcd") for _ in range(40)) for _ in range(5)]
    strings = [r.choice(stems) + bytes(r.choice(b"pq") for _ in range(10)) for _ in range(400)] + [bytes(r.randrange(256) for _ in range(50)) for _ in range(2000)]
    text = np.frombuffer(b"".join(strings) + bytes(64), dtype=np.uint8)
    starts, stats = np.arange(0, 50 * len(strings), 50), {}
    order, begins = suffix_dedup.multikey_quicksort(text, starts, 40, stats=stats)
    cut = [strings[i][:40] for i in order]
    assert cut == sorted(cut) and sorted(order.tolist()) == list(range(len(strings)))
    assert [cut[b] for b in begins] == sorted(set(cut))
    assert stats["split"] > 500 and stats["moved"] < 0.75 * stats["rounds"] * len(strings)  # the random ones drop out early
    kind = np.array([i % 3 for i in range(len(strings))])
    order, begins = suffix_dedup.multikey_quicksort(text, starts, 40, kind)
    assert [(int(kind[i]), strings[i][:40]) for i in order] == sorted((i % 3, s[:40]) for i, s in enumerate(strings))
    assert len(begins) == len({(i % 3, s[:40]) for i, s in enumerate(strings)})
    assert len(suffix_dedup.multikey_quicksort(text, starts[:0], 40)[0]) == 0


def brute_repeats(rows, length=50):
    out = Counter()
    todo = sorted((i if i is not None else -1, (t or "").encode()) for i, t in rows)
    least = {}
    for i, t in todo:
        for p in range(len(t) - length + 1):
            least[t[p : p + length]] = min(least.get(t[p : p + length], 1 << 60), i)
    for i, t in todo:
        gone = bytearray(len(t))
        for p in range(len(t) - length + 1):
            if least[t[p : p + length]] < i:
                gone[p : p + length] = b"\1" * length
        kept = bytes(c for c, g in zip(t, gone) if not g)
        spans = sum(1 for a, b in zip(b"\0" + bytes(gone), bytes(gone)) if b and not a)
        out[(i, len(t), sum(gone), spans, hashlib.sha256(kept).hexdigest())] += 1
    return out


@pytest.mark.parametrize(("block", "per"), [(1 << 22, 1 << 18), (4000, 64)])
def test_remove_repeats(docs, plain, empty, block, per):
    rows = suffix_dedup.remove_repeats(docs, block_bytes=block, anchors_per_range=per, with_spans=True).collect()
    assert Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in rows) == brute_repeats(plain)
    assert all(sum(s.end - s.begin for s in r.spans) == r.n_removed for r in rows)
    assert suffix_dedup.remove_repeats(empty).count() == 0


# ---- 4 exact dedup --------------------------------------------------------------------------------------------


def test_exact_groups(docs, plain, empty):
    rows = exact_dedup.exact_groups(docs).collect()
    sizes, keep = Counter(low(t) for _, t in plain), {}
    for i, t in plain:
        keep[low(t)] = max(i, keep.get(low(t), i))
    want = Counter((i, keep[low(t)], sizes[low(t)], hashlib.sha256(low(t)).hexdigest()) for i, t in plain)
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in rows) == want
    assert sum(r.kept for r in rows) == len(sizes)
    kept = exact_dedup.drop_copies(docs)
    assert kept.columns == docs.columns and Counter(low(r.text) for r in kept.collect()) == Counter(sizes.keys())
    assert exact_dedup.exact_groups(empty).count() == 0 and exact_dedup.drop_copies(empty).count() == 0


def test_codes_that_collide_are_told_apart(spark):
    chunks = spark.createDataFrame([(1, b"a"), (1, b"b"), (1, b"b"), (2, b"c")], "code long, digest binary")
    rows = {(r.code, bytes(r.digest)): r.variant for r in exact_dedup.verified_identifiers(chunks).collect()}
    assert rows == {(1, b"a"): 0, (1, b"b"): 1, (2, b"c"): 0}


# ---- 5 language id --------------------------------------------------------------------------------------------


def test_gru_gradients():
    m = language_id.ByteGru.new(["a", "b"], hidden=3)
    m.p = {k: v.astype(np.float64) for k, v in m.p.items()}
    x, y, w = language_id._pack([b"abc", b"zab"]), np.array([0, 1]), np.ones(2)
    _, g = m.gradients(x, y, w)
    for name, where in (("xf", (97, 4)), ("hb", (1, 7)), ("of", (2, 1)), ("bias", (0,))):
        keep = m.p[name][where]
        m.p[name][where] = keep + 1e-5
        up, _ = m.gradients(x, y, w)
        m.p[name][where] = keep - 1e-5
        down, _ = m.gradients(x, y, w)
        m.p[name][where] = keep
        assert g[name][where] == pytest.approx((up - down) / 2e-5, rel=2e-3, abs=1e-7)


def test_language_pools_all_positions():
    """The map's result equals a plain pass over every word, position by position, alone or in any batch."""
    m = language_id.ByteGru.new(["a", "b", "c"], hidden=5, seed=9)
    r = random.Random(1)
    texts = ["".join(r.choice("abcdé 世ß\n") for _ in range(n)) for n in (7, 40, 300, 900)] + [None, "", "12 ..."]
    got = language_id.Labeller(m).documents(texts)
    assert got[4:] == [("und", 0.0)] * 3
    for text, (lang, score) in zip(texts[:4], got):
        total, places = np.zeros(3), 0
        for word in text.lower().encode().split():
            for i in range(0, len(word), 30):
                prob = m.positions(np.frombuffer(b" " + word[i : i + 30] + b" ", dtype=np.uint8)[:, None])[:, 0]
                total, places = total + np.log(prob.astype(float)).sum(axis=0), places + len(prob)
        mean = total / places * min(places, 24)
        e = np.exp(mean - mean.max())
        assert lang == "abc"[int(mean.argmax())] and score == pytest.approx(float(e.max() / e.sum()), rel=1e-3)
        alone = language_id.Labeller(m).documents([text])[0]
        assert alone[0] == lang and alone[1] == pytest.approx(score, rel=1e-5)


def test_language_held_out_accuracy(spark, data, docs, empty):
    table = spark.read.parquet(f"{data}/documents.parquet")
    model = language_id.fit(table)
    rows = {r.doc_id: r for r in language_id.identify(table, model).collect()}
    truth = {r.doc_id: r.lang for r in table.collect()}
    held = [i for i in rows if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(rows[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i in rows)
    assert sum(rows[i].lang_pred == truth[i] for i in held) >= 0.9 * len(held)
    odd = {r.doc_id: r for r in language_id.identify(docs, model).collect()}
    assert odd[1].lang_pred == odd[2].lang_pred == odd[9].lang_pred == "und" and 0 <= odd[45].score <= 1
    assert language_id.fit(empty) is None and language_id.identify(docs, None).where("lang_pred <> 'und'").count() == 0
    assert language_id.identify(empty, model).count() == 0


# ---- 6 toxicity -----------------------------------------------------------------------------------------------


def test_ordinal_regression_orders_grades():
    r = random.Random(2)
    clean = [" ".join(r.choice(["sun", "sea", "wind", "tree"]) for _ in range(20)) for _ in range(60)]
    bad = [" ".join(r.choice(["sun", "sea", "wind"]) for _ in range(20 - k)) + " scum" * k for k in (1, 2, 3, 9, 10, 11) * 6]
    m = toxicity.fit_ordinal(clean + bad, [0] * 60 + [1] * 36)
    assert m.thresholds[0] < m.thresholds[1]
    none, some, much = (sum(m.above(t)) for t in (clean[0], "sun scum sea", "scum " * 12))
    assert none < 0.5 < some < much <= 2
    assert all(a >= b for a, b in [m.above(t) for t in clean + bad])


def test_severity_equals_its_formula(docs, plain):
    """Expected severity by hand from weights and thresholds; nothing to read has severity 0, whatever the thresholds."""
    m = toxicity.OrdinalModel({"w1": 0.7, "one": 1.3, "hello": -2.0, "quic-": 0.4}, (-0.5, 1.5))
    got = defaultdict(set)
    for r in toxicity.score(docs, m).collect():
        got[r.doc_id].add((round(r.p_toxic, 9), round(r.p_severe, 9), round(r.expected_severity, 9), r.grade))
    for i, t in plain:
        c = toxicity.features(t)
        x = sum(w * (1 + math.log(c[f])) for f, w in m.weights.items() if c[f])
        p = [1 / (1 + math.exp(k - x)) for k in m.thresholds] if any(map(str.isalpha, t or "")) else [0.0, 0.0]
        mass = [1 - p[0], p[0] - p[1], p[1]]
        assert (round(p[0], 9), round(p[1], 9), round(sum(p), 9), mass.index(max(mass))) in got[i]
    assert all(got[i] == {(0.0, 0.0, 0.0, 0)} for i in (1, 2, 3, 9))


def test_the_cutoff_is_chosen_on_what_a_trial_leaves_out():
    """By hand: of single cutoffs, fitted without the third put aside, the one that tells that third best; then all texts."""
    import pyarrow.parquet as pq

    text = {r["doc_id"]: r["text"] for r in pq.read_table("/root/testdata/sf0.01/documents.parquet").to_pylist()}
    rows = [(text[r["doc_id"]], r["toxic"]) for r in pq.read_table("/root/testdata/sf0.01/labels.parquet").to_pylist() if r["toxic"] is not None and text.get(r["doc_id"])]
    third = [r for r in rows if zlib.crc32(r[0].encode()) % 3 == 0]
    others = [r for r in rows if zlib.crc32(r[0].encode()) % 3 != 0]
    score = {}
    for z in (2.0, 3.0, 5.0):
        m = toxicity.fit_ordinal(*zip(*others), cutoffs=(z,))
        chance = [1 / (1 + math.exp(m.thresholds[0] - (m.margin(t) or 0.0))) for t, _ in third]
        score[z] = sum(math.log(c if toxic else 1 - c) for c, (_, toxic) in zip(chance, third))
    best = max(score, key=score.get)
    got, want = toxicity.fit_ordinal(*zip(*rows), cutoffs=(2.0, 3.0, 5.0)), toxicity.fit_ordinal(*zip(*rows), cutoffs=(best,))
    assert got.weights == want.weights and got.thresholds == want.thresholds and got.weights
    few = [("scum scum", 1), ("sun sea", 0)] * 4  # equal texts fall on one side: nothing to choose by
    assert toxicity.fit_ordinal(*zip(*few)).weights == toxicity.fit_ordinal(*zip(*few), cutoffs=(2.0,)).weights


def test_toxicity_held_out():
    """Fitted on two thirds of the labelled rows, the others are told apart."""
    import pyarrow.parquet as pq

    text = {r["doc_id"]: r["text"] for r in pq.read_table("/root/testdata/sf0.1/documents.parquet").to_pylist()}
    rows = [(text[r["doc_id"]], r["toxic"], r["doc_id"]) for r in pq.read_table("/root/testdata/sf0.1/labels.parquet").to_pylist() if r["toxic"] is not None and r["doc_id"] in text]
    held = [r for r in rows if zlib.crc32(str(r[2]).encode()) % 3 == 0]
    known = [r for r in rows if zlib.crc32(str(r[2]).encode()) % 3 != 0]
    m = toxicity.fit_ordinal([r[0] for r in known], [r[1] for r in known])
    caught = [m.above(t)[0] >= 0.5 for t, toxic, _ in held if toxic]
    kept = [m.above(t)[0] < 0.5 for t, toxic, _ in held if not toxic]
    print("held out:", len(caught), "toxic, caught", sum(caught) / len(caught), ";", len(kept), "clean, kept", sum(kept) / len(kept))
    assert sum(caught) >= 0.8 * len(caught) and sum(kept) >= 0.97 * len(kept)


def test_toxicity_on_tables(spark, data, docs, empty):
    table, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = toxicity.fit(table, labels)
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    found = {r.doc_id: r for r in toxicity.score(table, model).collect()}
    assert not any(found[i].toxic for i, t in truth.items() if not t)
    assert sum(found[i].toxic for i, t in truth.items() if t) >= 0.6 * sum(truth.values())
    assert all(0 <= r.expected_severity <= 2 for r in found.values())
    kept = toxicity.drop_toxic(table, model)
    assert kept.columns == table.columns and {r.doc_id for r in kept.collect()} == {i for i, r in found.items() if not r.toxic}
    assert toxicity.score(docs, model).count() == docs.count()
    assert toxicity.fit(empty, labels.limit(0)).weights == {} and toxicity.score(docs, toxicity.OrdinalModel()).where("toxic").count() == 0
    assert toxicity.score(empty, model).count() == 0


# ---- 7 SentencePiece ------------------------------------------------------------------------------------------


def test_streaming_viterbi_is_the_best_segmentation():
    v = pieces.Vocabulary.load(pieces.default_model())
    r = random.Random(4)
    for _ in range(150):
        text = "▁" + "".join(r.choice("abcdeéß世界thinoer▁😀\n") for _ in range(r.randint(1, 160)))
        best = [(0.0, [])] + [None] * len(text)
        for j in range(1, len(text) + 1):
            options = []
            for i in range(max(0, j - v.longest), j):
                hit = v.pieces.get(text[i:j])
                if hit:
                    options.append((best[i][0] + hit[1], best[i][1] + [hit[0]]))
                elif j == i + 1:
                    raw = text[i].encode()
                    options.append((best[i][0] + v.byte_score * len(raw), best[i][1] + [v.byte_ids[b] for b in raw]))
            best[j] = max(options, key=lambda o: o[0])
        search = pieces.StreamingViterbi(v, check=16)
        parts = list(search.encode(text[i : i + 7] for i in range(0, len(text), 7)))
        assert [x for p in parts for x in p] == best[-1][1]


def test_viterbi_window_stays_small():
    v = pieces.Vocabulary.load(pieces.default_model())
    search = pieces.StreamingViterbi(v)
    n = sum(len(p) for p in search.encode("information" for _ in range(3000)))
    assert n > 3000 and search.peak < 20 * v.longest


def best_segmentation(v, text):
    best = [(0.0, [])] + [None] * len(text)
    for j in range(1, len(text) + 1):
        options = []
        for i in range(max(0, j - v.longest), j):
            hit = v.pieces.get(text[i:j])
            if hit:
                options.append((best[i][0] + hit[1], best[i][1] + [hit[0]]))
            elif j == i + 1:
                raw = text[i].encode()
                options.append((best[i][0] + v.byte_score * len(raw), best[i][1] + [v.byte_ids[b] for b in raw]))
        best[j] = max(options, key=lambda o: o[0])
    return best[-1][1]


def test_documents_stream_through_one_search(plain):
    """The ids of whole documents are the best segmentation's; commits come at word ends, and inside stretches without any."""
    v = pieces.Vocabulary.load(pieces.default_model())
    assert v.words_stand_alone
    texts = [t for _, t in plain if t and len(t) < 4000] + ["a  b   c ", " lead", "x" * 700 + " y " + "information" * 90]
    for part in (7, 50, 1 << 14):
        search, known = pieces.StreamingViterbi(v), {}
        for t in texts[:: 1 if part == 50 else 5]:
            marked = "▁" + t.replace(" ", "▁")
            ids = array("i")
            for piece in search.document((marked[i : i + 11] for i in range(0, len(marked), 11)), known, part=part):
                ids.frombytes(piece)
            assert ids.tolist() == best_segmentation(v, marked)
    words = " ".join(f"word{i}" for i in range(2000))
    search = pieces.StreamingViterbi(v)
    list(search.document(["▁" + words.replace(" ", "▁")]))
    assert search.commits == 2000 and search.peak < 4 * v.longest
    search = pieces.StreamingViterbi(v)
    list(search.document((("information" * 20) for _ in range(200)), part=64))
    assert search.early > 500 and search.peak < 20 * v.longest


def test_query_digests_are_those_of_the_best_segmentation(docs, plain):
    v = pieces.Vocabulary.load(pieces.default_model())
    got = defaultdict(set)
    for r in pieces.round_trip(docs).collect():
        got[r.doc_id].add((r.n_ids, r.ids_sha256))
    for i, t in plain[:25]:
        ids = array("i", best_segmentation(v, "▁" + t.replace(" ", "▁")) if t else [])
        assert (len(ids), hashlib.sha256(ids.tobytes()).hexdigest()) in got[i]


def test_pieces_round_trip(docs, plain, empty):
    import sentencepiece

    rows = pieces.round_trip(docs).collect()
    assert len(rows) == len(plain) and all(r.lossless for r in rows)
    library = sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())
    codec = pieces.Codec(pieces.Vocabulary.load(pieces.default_model()))
    for _, t in plain[:30]:
        ids = array("i")
        ids.frombytes(codec.encode(t))
        assert library.decode(list(ids)) == codec.decode(ids.tobytes())
    back = pieces.decode(pieces.encode(docs))
    assert Counter((r.doc_id, r.text) for r in back.collect()) == Counter((i, (t or "").replace("▁", " ")) for i, t in plain)
    assert pieces.round_trip(empty).count() == 0


# ---- 8 deleted interpolation ----------------------------------------------------------------------------------


def test_interpolation_base_and_model(docs, plain, empty):
    train = [low(t).split() + [None] for i, t in plain if zlib.crc32(str(i).encode()) % 7 != 2]
    c = Counter(w for d in train for w in d)
    n, v = sum(c.values()), len(c)
    runs = []
    for options in ({}, {"block_bytes": 3000, "keys_per_range": 50}):
        rows = interpolation.score(docs, **options).collect()
        assert len(rows) == len(plain)
        want = defaultdict(list)
        for i, t in plain:
            w = low(t).split() + [None]
            want[i].append((len(w), sum(c[x] > 0 for x in w), sum(math.log10((c[x] + 1) / (n + v + 1)) for x in w)))
        for r in rows:
            assert r.train_tokens == n and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2)
            assert any((r.n_tokens, r.n_known) == x[:2] and r.base_score == pytest.approx(x[2], abs=1e-7) for x in want[r.doc_id])
        scores = sorted((r.doc_id, r.score) for r in rows)
        runs.append([s for _, s in scores])
        assert sum(r.score for r in rows if r.held_out) > sum(r.base_score for r in rows if r.held_out)
    assert runs[0] == pytest.approx(runs[1])  # the same whatever the blocks
    assert interpolation.score(empty).count() == 0


def test_weights_are_a_distribution():
    code = np.array([(3 << 22) | (600 << 11) | 700, (3 << 22) | (600 << 11), 0, (9 << 22) | (520 << 11) | 530])
    w = interpolation.learn_weights(code, np.array([5.0, 2.0, 1.0, 4.0]))
    assert w.min() >= 0 and w.sum(axis=1) == pytest.approx(np.ones(interpolation.BUCKETS)) and w[0, 2] == 0


# ---- 9 token counts -------------------------------------------------------------------------------------------


def test_token_counts_equal_the_library(docs, plain, empty, spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(token_counts.default_tokenizer())
    special = [(100, "a <|endoftext|> b"), (101, "x" * 70_000), (102, ("abc def\nghi " * 9000) + "  tail \n\n")]
    df = docs.select("doc_id", "text").unionByName(spark.createDataFrame(special, "doc_id long, text string"))
    rows = token_counts.count_tokens(df).collect()
    want = Counter()
    for i, x in plain + special:
        n = len(t.encode(x or "", add_special_tokens=False))
        want[(i, len((x or "").encode()), n, n > 512)] += 1
    assert Counter(map(tuple, rows)) == want
    assert len(token_counts.safe_parts(special[2][1])) > 1 and "".join(token_counts.safe_parts(special[2][1])) == special[2][1]
    assert token_counts.count_tokens(empty).count() == 0


# ---- 10 n-gram Jaccard join -----------------------------------------------------------------------------------


def brute_groups(rows, width, percent):
    sets, parent = [], list(range(len(rows)))
    for _, t in rows:
        w = low(t).split()
        sets.append(set(zip(*(w[k:] for k in range(width)))) if len(w) >= width else ({tuple(w)} if w else set()))

    def root(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            linked = both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both)
            if linked or (rows[a][0] == rows[b][0] and sets[a] and sets[b]):
                parent[root(a)] = root(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        least[root(k)] = min(i, least.get(root(k), i))
    return Counter((i, len(sets[k]), least[root(k)]) for k, (i, _) in enumerate(rows))


@pytest.mark.parametrize(("width", "percent", "options"), [(3, 90, {}), (5, 80, {}), (2, 60, {"costly": 2, "block_keys": 300, "keys_per_range": 40, "pivots": 1}), (1, 50, {"costly": 3, "most_l": 4})])
def test_similar_groups(docs, plain, empty, width, percent, options):
    rows = jaccard_join.similar_groups(docs, width=width, percent=percent, **options).collect()
    assert Counter(map(tuple, rows)) == brute_groups(plain, width, percent)
    if not options:
        assert jaccard_join.similar_groups(empty, width=width, percent=percent).count() == 0


def test_random_families(spark):
    """Many near copies of few originals, hubs present or not: all components are found."""
    r = random.Random(8)
    rows = []
    for f in range(4):
        base = [f"t{r.randrange(90)}" for _ in range(60)]
        for _ in range(40):
            own = list(base)
            for _ in range(r.randint(0 if f % 2 else 1, 5)):
                own[r.randrange(60)] = f"u{r.randrange(200)}"
            rows.append((len(rows), " ".join(own)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for percent in (70, 85):
        got = jaccard_join.similar_groups(df, width=2, percent=percent, costly=6).collect()
        assert Counter(map(tuple, got)) == brute_groups(rows, 2, percent)


def test_components_of_a_long_chain(spark):
    links = spark.createDataFrame([(k, k + 1) for k in range(60)] + [(100, 200), (200, 300)], "x long, y long")
    got = {r.node: r.component for r in components.connected_components(links).collect()}
    assert all(got[k] == 0 for k in range(61)) and {got[k] for k in (100, 200, 300)} == {100}


def test_null_ids(spark):
    df = spark.createDataFrame([(None, "a b c d e"), (None, None), (1, "a b c d e"), (2, "x")], "doc_id long, text string").selectExpr("*", "'en' AS lang", "'s' AS source")
    assert {r.component_id for r in jaccard_join.similar_groups(df).collect()} == {None, 2}
    assert {(r.doc_id, r.keep_id) for r in exact_dedup.exact_groups(df).collect()} == {(None, 1), (None, None), (1, 1), (2, 2)}
    for out in (mixing.mix(df), media.media_features(df), suffix_dedup.remove_repeats(df), interpolation.score(df), token_counts.count_tokens(df), pieces.round_trip(df), language_id.identify(df, None)):
        assert out.count() == 4
