"""Every stage of the pipeline on nulls, empty and repeated rows, empty tables and columns whose names clash."""

import numpy as np
import pytest

import corpus_pipeline

LONG = " ".join(f"word{i} and" for i in range(60))
ROWS = [
    (1, LONG, "en", "a", 5),
    (1, LONG, "en", "a", 5),
    (1, LONG + " end", "en", "a", 5),
    (2, LONG + " end", None, None, None),
    (None, "".join(f"other{i} " for i in range(40)), "en", "a", 1),
    (None, "".join(f"third{i} " for i in range(40)) + 'token = "9f86d081884c7d659a2feaa0c55ad015a3bf4f1b"', "en", "b", 7),
    (3, None, None, None, None),
    (4, "", "en", "b", 0),
    (5, "x " * 5000, "de", "b", 10_000),
    (6, "é" * 4000 + " " + LONG[::-1], "fr", "c", 1),
]


@pytest.fixture(scope="module")
def table(spark):
    df = spark.createDataFrame(ROWS, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    names = ("n_words", "kept", "fp", "component_id", "found", "pieces", "size", "taken", "shards", "start", "offset", "_text", "_host", "_tag", "KEY")
    return df.selectExpr("*", *[f"'{n}' as `{n}`" for n in names])


@pytest.mark.parametrize("name,stage", corpus_pipeline.STAGES)
def test_stage_keeps_columns_and_takes_an_empty_table(spark, table, name, stage):
    got, none = stage(spark, table, ""), stage(spark, table.limit(0), "")
    assert none.count() == 0 and none.columns == got.columns
    if name != "pack":
        assert got.columns == table.columns
        assert [f.dataType for f in got.schema] == [f.dataType for f in table.schema]
        clash = got.select("n_words", "kept", "fp", "size", "_text", "KEY").distinct().collect()
        assert [tuple(r) for r in clash] == [("n_words", "kept", "fp", "size", "_text", "KEY")]


def test_rules_keep_clean_rows_as_they_are(spark, table):
    kept = corpus_pipeline.quality_rules(spark, table, "").select("doc_id", "text").collect()
    assert sorted((r["doc_id"] or 0, r["text"]) for r in kept) == sorted((r[0] or 0, r[1]) for r in ROWS if r[1] and len(r[1].split()) >= 20 and not r[1].startswith("x "))


def test_one_row_of_each_group_stays(spark, table):
    kept = corpus_pipeline.near_duplicates(spark, table, "").select("doc_id", "text").collect()
    # the two long texts and their copies are one group, though its smallest id stands on three rows of two texts
    assert sum(r["doc_id"] in (1, 2) for r in kept) == 1
    assert sum(r["doc_id"] is None for r in kept) == 2
    # a null text is as an empty one
    assert sorted(r["doc_id"] for r in kept if r["doc_id"]) == [1, 3, 5, 6]


def test_secrets_go_and_nothing_else_changes(spark, table):
    made = corpus_pipeline.secret_scan(spark, table, "").select("doc_id", "text", "n_chars").collect()
    before = sorted((str(r[0]), str(r[1]), str(r[4])) for r in ROWS)
    after = sorted((str(r["doc_id"]), str(r["text"]), str(r["n_chars"])) for r in made)
    changed = [x for x in after if x not in before]
    assert len(made) == len(ROWS) and len(changed) == 1 and "[secret]" in changed[0][1] and changed[0][2] == str(len(changed[0][1]))


def test_mix_takes_rows_as_they_are_and_near_each_target(spark, table):
    from bucketcsr.llm import mixing

    drawn = corpus_pipeline.source_mix(spark, table, "").select("source", "text").collect()
    assert {(r["source"], r["text"]) for r in drawn} <= {(r[3], r[1]) for r in ROWS}
    mixed = mixing.mix(table, keep=["doc_id", "source"]).collect()
    assert len(mixed) == len(ROWS)
    for source in {r[3] for r in ROWS}:
        rows = [r for r in mixed if r["source"] == source]
        sizes = [r["size"] for r in rows]
        assert sum(sizes) == rows[0]["source_size"] and all(r["taken"] <= 3 * r["size"] for r in rows)
        assert abs(sum(r["taken"] for r in rows) - rows[0]["target"]) <= max(sizes, default=0)
        assert sum(r["taken"] for r in rows) == sum(len(d["text"].split()) for d in drawn if d["source"] == source and d["text"])


def test_too_many_sources_are_refused(spark, table):
    from bucketcsr.llm import mixing

    with pytest.raises(ValueError):
        mixing.mix(table, plan=mixing.MixPlan(most_sources=2))


def test_pack_holds_every_row(spark, table):
    pieces = corpus_pipeline.pack(spark, table, "").toPandas()
    whole = pieces.groupby(pieces.doc_id.fillna(-1)).length.sum()
    assert (pieces.start == 0).sum() == len(ROWS) and (whole > 0).all()
    for _, g in pieces.sort_values("offset").groupby("sequence_id"):
        assert (g.offset.values == np.concatenate(([0], g.length.cumsum()[:-1]))).all() and g.length.sum() <= 2048


def test_texts_are_linked_by_the_trees_of_fingerprints(spark):
    """Two texts whose fingerprints differ in two bits or fewer are one group, though their shingles are similar to 10/13 only."""
    import pyarrow as pa

    from bucketcsr.llm import simhash

    short = [" ".join(f"w{i}x{k}" for k in range(14)) for i in range(12_000)]
    long = [t + "".join(f" w{i}x{k}" for k in range(14, 17)) for i, t in enumerate(short)]
    a, b = (simhash.shingle_sets(pa.array(t), simhash.Similarity())[0].to_pylist() for t in (short, long))
    near = next(i for i in range(len(a)) if ((a[i] ^ b[i]) & (2**64 - 1)).bit_count() <= 2)
    far = next(i for i in range(len(a)) if ((a[i] ^ b[i]) & (2**64 - 1)).bit_count() > 9)
    rows = [(1, short[near], "en", "a", 1), (2, long[near], "en", "a", 1), (3, short[far], "en", "a", 1), (4, long[far], "en", "a", 1)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    assert sorted(r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()) == [1, 3, 4]
