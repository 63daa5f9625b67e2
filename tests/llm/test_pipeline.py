"""The pipeline's stages against brute force, each on its own input."""

from collections import Counter

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from gapweave.llm import mixing, toxicity  # noqa: E402

from .test_operators import brute_groups, low  # noqa: E402


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    columns = docs.columns
    assert [k for k, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "ngram_jaccard_join", "mixing", "sentencepiece"]
    model = toxicity.fit(docs, spark.read.parquet(f"{data}/labels.parquet"))
    rows = [r for r in docs.collect() if model.above(r.text)[0] < 0.5]
    step = {k: f for k, f in corpus_pipeline.STAGES}

    got = step["toxicity"](spark, docs, data)
    assert got.columns == columns and Counter(map(tuple, got.collect())) == Counter(map(tuple, rows))

    frame = spark.createDataFrame(rows, docs.schema)
    keep = {}
    for r in rows:
        if r.doc_id >= keep.get(low(r.text), r).doc_id:
            keep[low(r.text)] = r
    got = step["exact_dedup"](spark, frame, data)
    assert got.columns == columns and Counter(map(tuple, got.collect())) == Counter(map(tuple, keep.values()))

    rows = sorted(keep.values())
    frame = spark.createDataFrame(rows, docs.schema)
    alone = {i for i, _, c in brute_groups([(r.doc_id, r.text) for r in rows], 5, 80) if i == c}
    got = step["ngram_jaccard_join"](spark, frame, data)
    assert got.columns == columns and {r.doc_id for r in got.collect()} == alone

    mixed = step["mixing"](spark, got, data)
    assert mixed.columns == columns
    assert sum(len(low(r.text).split()) for r in mixed.collect()) == sum(r.taken for r in mixing.mix(got).collect())

    out = step["sentencepiece"](spark, mixed, data)
    assert out.count() == mixed.count() and out.where("NOT lossless").count() == 0


def test_run(spark, data):
    out = corpus_pipeline.run(spark, data)
    assert out.count() > 0 and out.where("NOT lossless").count() == 0


CLASHES = "row string, id long, sha string, kept boolean, keep_id long, keep_sha string, _kept long, _id long, _size int, _source string, _draw long, _bucket int, _copy int, _row string, part int, share double, target double, whole int, rest double, edge int, last string, source_size long, component string, component_id long, n long, repeats int, p double, mild double"


def clashing(spark, rows):
    """Documents with columns named as the stages name theirs, each with a value of its own row."""
    kinds = [c.strip().split() for c in CLASHES.split(",")]
    value = {"string": lambda k, c: f"{c}{k}", "long": lambda k, c: 1000 + k, "int": lambda k, c: 2000 + k, "double": lambda k, c: k + 0.5, "boolean": lambda k, c: k % 2 == 0}
    full = [(i, t, "en", s, len(t or ""), *[value[kind](k, c) for c, kind in kinds]) for k, (i, t, s) in enumerate(rows)]
    return spark.createDataFrame(full, "doc_id long, text string, lang string, source string, n_chars long, " + CLASHES)


def test_clashing_columns_keep_their_values(spark, data):
    """Every row that a stage returns is one of its input's, value by value, whatever the columns are called."""
    base = " ".join(f"w{i}" for i in range(60))
    rows = [(1, base, "a"), (2, base, "b"), (3, base.replace("w7 ", "v7 "), "a"), (4, "quite another text of its own", "b"), (5, None, None), (6, "", "a"), (None, "no id here", "a"), (7, "short", None)]
    docs = clashing(spark, rows).repartition(2)
    before = Counter(map(str, docs.collect()))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, data)
        assert out.columns == docs.columns, name
        got = Counter(map(str, out.collect()))
        assert got and set(got) <= set(before), name
        if name != "mixing":
            assert all(n == 1 for n in got.values()), name
    assert {r.doc_id for r in corpus_pipeline.drop_exact_copies(spark, docs, data).collect()} == {2, 3, 4, 6, None, 7}
    assert {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, data).collect()} == {1, 4, 5, 6, None, 7}
    assert corpus_pipeline.encode_pieces(spark, docs, data).count() == len(rows)


@pytest.mark.parametrize("rows", [[], [(None, None, None)] * 3])
def test_empty_and_null_tables_go_through(spark, data, rows):
    docs = clashing(spark, rows)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, data)
        assert out.columns == docs.columns, name
        n = out.count()
        assert n == (0 if name == "mixing" else len(rows) and (1 if name == "exact_dedup" else 3)), name
    assert corpus_pipeline.encode_pieces(spark, docs, data).count() == len(rows)
