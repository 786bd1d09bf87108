"""Hard inputs: strings built against polynomial hashes, clashing column names, cycles and repeated ids in reply tables."""

import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from floorwalk.llm import chat_format, mixing, packing, quality_rules, suffix_dedup
from floorwalk.llm.textkit import HASH_A, HASH_B, chunks
from tests.llm.test_operators import SCHEMA, brute_suffix, corpus

FLIP = str.maketrans("ab", "ba")


def thue_morse(n):
    text = "a"
    while len(text) < n:
        text += text.translate(FLIP)
    return text


@pytest.mark.parametrize("n", [256, 512, 1024, 2048, 4096])
def test_hashes_tell_thue_morse_strings_apart(n):
    one = thue_morse(n)
    data = np.frombuffer((one + one.translate(FLIP) + one).encode(), dtype=np.uint8)
    for hashed in (HASH_A, HASH_B):
        a, b, c = hashed.spans(hashed.prefix(data), np.array([0, n, 2 * n]), np.array([n, 2 * n, 3 * n]))
        assert a == c and a != b
    words = (data.astype(np.uint64) << np.uint64(31)) + np.uint64(5)
    a, b, c = HASH_B.spans(HASH_B.prefix(words), np.array([0, n, 2 * n]), np.array([n, 2 * n, 3 * n]))
    assert a == c and a != b


def test_hashes_of_equal_spans_are_equal_across_blocks():
    data = np.random.default_rng(3).integers(0, 256, 9000).astype(np.uint8)
    twice = np.concatenate([data, data, data[:4096]])
    for hashed in (HASH_A, HASH_B):
        prefix = hashed.prefix(twice)
        start = np.array([0, 1, 4095, 4096, 4097, 8000])
        end = np.array([4096, 9, 4097, 8192, 9000, 9000])
        assert np.array_equal(hashed.spans(prefix, start, end), hashed.spans(prefix, start + 9000, end + 9000))
        assert len(set(hashed.spans(prefix, np.zeros(9000, np.int64), np.arange(9000)).tolist())) == 9000


@pytest.mark.parametrize("n", [256, 1024, 2048, 4096])
def test_operators_tell_thue_morse_strings_apart(spark, n):
    one, two = thue_morse(n), thue_morse(n).translate(FLIP)
    cache = packing.WordCache(packing.vocabulary())
    (chunk,) = chunks(pa.array([f"{one} {two}"]))
    assert cache.encode(chunk)[0].tolist() == cache.tokenizer.encode(f"{one} {two}", add_special_tokens=False).ids
    stats = quality_rules.text_statistics(pa.array([f"{one}\n{two}\n{one}", one, two]))
    assert stats["n_dup_lines"].tolist() == [1, 0, 0] and len(set(stats["text_hash"].tolist())) == 3
    assert len(set(stats["line_hash"][0].tolist())) == 2
    rows = [(1, one, "en", "s", 0, 0.0, "x"), (2, f"x{two}y{two}", "en", "s", 0, 0.0, "x")]
    found = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.deduplicate(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert found == brute_suffix(rows)


CLASHES = ("removed_lines", "_rid", "runs", "n_bytes", "kept_text", "size", "taken", "cut", "copies", "epochs", "slice", "key", "code", "root", "rid", "host", "label", "w0", "extra_3")


def test_stages_pass_columns_of_any_name(spark):
    docs = spark.createDataFrame(corpus(), SCHEMA)
    wide = docs.withColumns({c: F.concat(F.lit(f"{c}-"), F.coalesce(F.col("doc_id").cast("string"), F.lit("none"))) for c in CLASHES})
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, wide, "")
        assert out.columns == wide.columns, name
        rows = out.select("doc_id", *CLASHES).collect()
        assert rows and all(r[c] == f"{c}-{r.doc_id}" for r in rows for c in CLASHES), name
    assert packing.pack(wide).count() == packing.pack(docs).count()


@pytest.mark.parametrize("stage", corpus_pipeline.STAGES, ids=lambda s: s[0])
def test_stages_take_nulls_everywhere_and_empty_tables(spark, stage):
    nothing = spark.createDataFrame([(None,) * 7, (None, "", None, None, None, None, None), (4, None, None, None, None, None, None)], SCHEMA)
    out = stage[1](spark, nothing, "").collect()
    assert len(out) == {"quality_rules": 0, "simhash_dedup": 1, "suffix_dedup": 3, "source_mixing": 0, "packing": 3}[stage[0]]
    empty = spark.createDataFrame([], SCHEMA)
    assert stage[1](spark, empty, "").isEmpty()


def test_mixing_spreads_rows_without_an_id(spark):
    rows = [(None, f"w{i} " * 5, "en", "s", 0, 0.0, "x") for i in range(300)]
    mixed = mixing.mix(spark.createDataFrame(rows, SCHEMA), slices=16)
    assert mixed.agg(F.sum("taken")).first()[0] == 1500
    keys = {zlib.crc32(str(i).encode()) for i in range(3)}
    assert len(keys) == 3


def test_reply_cycles_are_left_out(spark):
    rows = [("a", "b", "user", "1", 1.0), ("b", "c", "user", "2", 1.0), ("c", "a", "user", "3", 1.0), ("d", "a", "user", "4", 1.0), ("self", "self", "user", "5", 1.0), ("r", None, "user", "6", 1.0), ("s", "r", "assistant", "7", 1.0)]
    trees = chat_format.format_trees(spark.createDataFrame(rows, "node string, parent string, role string, text string, score double"), 1)
    got = {r.root: chat_format.read_back(r.formatted) for r in trees.collect()}
    assert got == {"self": [("user", "5")], "r": [("user", "6"), ("assistant", "7")]}


def test_repeated_message_ids_stand_once(spark):
    rows = [("r", None, "user", "q", 1.0), ("a", "r", "assistant", "z", 1.0), ("a", "r", "assistant", "b", 9.0), (None, "r", "user", "lost", 1.0)]
    trees = chat_format.format_trees(spark.createDataFrame(rows, "node string, parent string, role string, text string, score double"), 1)
    assert [chat_format.read_back(r.formatted) for r in trees.collect()] == [[("user", "q"), ("assistant", "b")]]
