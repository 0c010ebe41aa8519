"""Nulls in any column, empty and very long texts, ties and repeated rows, empty tables, clashing names: every operator and stage."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from keyloom.llm import byte_bpe, cap_filters, language_rank, license_scan, multiset_fingerprint, secret_cnn, shard_minimax, simhash_mih, source_mix, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "worthless under the mit license token = 'abcdef0123456789' the quick brown fox\n" * 4000
ROWS = [
    (1, "the cat sat on the mat and the dog sat on the log", "en", "a", 1),
    (1, "the cat sat on the mat and the dog sat on the log", "en", "a", 1),
    (2, "the cat sat on the mat and the dog sat on the log", "en", "b", 1),
    (3, None, None, None, None),
    (4, "", "en", "a", 0),
    (None, "le chat est sur la table et le chien est dans la maison", "fr", None, 5),
    (6, LONG, "en", "c", len(LONG)),
    (7, " \t\n\x0b\f\r", None, "c", 6),
    (8, "été über ñandú 漢字   x😀y", "fr", "", 3),
    (9, "....,,,;;;", "en", "a", 10),
]
LABELS = [(1, 1, 0), (2, 1, 0), (6, 0, 1), (None, 1, 1), (8, None, None), (9, 1, 0)]
#: Names that the operators use inside.
CLASHES = ["h", "size", "fp", "node", "rep", "a", "b", "key", "u", "v", "value", "part", "nth", "bin", "row", "s", "id", "kept_id", "toxic", "score", "n", "g", "x", "times", "whole", "cut", "_nth", "filters", "ids", "found", "component_id", "shard", "slot", "ghost", "at", "which"]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame(LABELS, "doc_id long, quality int, toxic int")


DIGESTS = {
    "license_scan": lambda d, l: license_scan.digest(d),
    "byte_bpe": lambda d, l: byte_bpe.digest(d),
    "language_rank": lambda d, l: language_rank.digest(d),
    "source_mix": lambda d, l: source_mix.taken(d),
    "shard_minimax": lambda d, l: shard_minimax.digest(d),
    "simhash_mih": lambda d, l: simhash_mih.digest(d),
    "toxicity": toxicity.digest,
    "multiset_fingerprint": lambda d, l: multiset_fingerprint.digest(d),
    "secret_cnn": lambda d, l: secret_cnn.digest(d),
}


def clashing(df):
    return df.select("*", *[F.lit("x").alias(c) for c in CLASHES if c not in df.columns])


@pytest.mark.parametrize("name", DIGESTS)
def test_one_row_for_each_document(name, docs, labels):
    rows = DIGESTS[name](docs, labels).collect()
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0) for r in rows) == sorted((r[0] is None, r[0] or 0) for r in ROWS)


@pytest.mark.parametrize("name", DIGESTS)
def test_clashing_names_change_nothing(name, docs, labels):
    own = sorted(map(repr, DIGESTS[name](docs, labels).collect()))
    other = sorted(map(repr, DIGESTS[name](clashing(docs), labels.withColumn("text", F.lit("x")).withColumn("l_id", F.lit(1))).collect()))
    if name == "shard_minimax":  # slots of equal rows may change places
        own, other = len(own), len(other)
    assert own == other


@pytest.mark.parametrize("name", DIGESTS)
def test_empty_table(name, docs, labels):
    assert DIGESTS[name](docs.limit(0), labels.limit(0)).collect() == []


@pytest.mark.parametrize("name", DIGESTS)
def test_all_null(name, spark, labels):
    rows = spark.createDataFrame([(None, None, None, None, None)] * 3, SCHEMA)
    assert len(DIGESTS[name](rows, labels).collect()) == 3


def test_no_labels(docs, labels):
    assert {r["predicted"] for r in toxicity.digest(docs, labels.limit(0)).collect()} == {0}


@pytest.mark.parametrize("stage", corpus_pipeline.STAGES, ids=lambda s: s[0])
def test_stages_on_odd_rows(stage, spark, docs, labels, tmp_path):
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    name, f = stage
    for rows in (docs, clashing(docs), docs.limit(0)):
        out = f(spark, rows, str(tmp_path))
        if name != "byte_bpe":
            assert out.columns == rows.columns
        assert out.count() <= 3 * len(ROWS)


def test_pipeline_runs(spark, docs, labels, tmp_path):
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).columns == ["doc_id", "n_tokens", "ids"]


def test_odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    one = [1.0, 0.5, 0.25, 0.0]
    rows = [(1, one), (2, one), (2, one), (3, [2.0, 1.0, 0.5, 0.0]), (4, None), (5, []), (6, [0.0] * 4), (7, [nan, 1.0, 1.0, 1.0]), (8, [inf, 1.0, 1.0, 1.0]), (9, [1.0, None, 1.0, 1.0]), (None, one), (10, [1.0, 2.0]), (11, [-1.0, -0.5, -0.25, 0.0]), (12, None)]
    for kind in ("float", "double"):
        found = {r["vec_id"]: r for r in cap_filters.digest(clashing(spark.createDataFrame(rows, f"vec_id long, embedding array<{kind}>"))).collect()}
        assert {k for k, r in found.items() if r["n_links"]} == {1, 2, 3}
        assert {found[k]["component_id"] for k in (1, 2, 3)} == {1} and found[1]["kept"] and not found[2]["kept"]
        assert all(found[k]["component_id"] == k and found[k]["kept"] for k in (4, 5, 6, 7, 8, 9, 10, 11, 12))
        assert found[None]["n_links"] == 0 and found[None]["component_id"] is None
    assert cap_filters.digest(spark.createDataFrame([], "vec_id long, embedding array<float>")).collect() == []
    assert [r["n_links"] for r in cap_filters.digest(spark.createDataFrame([(1, None)], "vec_id long, embedding array<float>")).collect()] == [0]
