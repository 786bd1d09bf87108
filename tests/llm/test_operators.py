"""Operators against brute force, round trips and held-out accuracy, on small fixtures with hard cases."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from floorwalk.llm import byte_cnn, cap_filters, chat_format, context_mixing, mixing, packing, quality_rules, simhash_dedup, suffix_dedup, weak_labels
from floorwalk.llm.runtime import connected_components
from floorwalk.llm.textkit import chunks

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, path string"


def corpus() -> list[tuple]:
    rng = random.Random(3)
    word = lambda: "".join(rng.choice(["an", "the", "ou", "ti", "re", "sh", "é", "ß"]) for _ in range(rng.randint(1, 4)))
    text = lambda n: " ".join(word() for _ in range(n))
    shared, base = text(60), text(200)
    rows = [(i, f"{text(20)}\n{shared if i % 3 == 0 else text(30)}\n{text(15)}.", "en", f"src{i % 4}") for i in range(24)]
    rows += [(100 + i, base, "fr", "src0") for i in range(5)]
    rows += [(200 + i, base.replace(" ", "  ", i) + f" tail{i}", "fr", "src1") for i in range(4)]
    rows += [(300, None, None, None), (301, "", "en", "src0"), (302, "   \n\t", "en", None), (303, "Hi.", None, "src2"), (304, "\x00 b\x0bc \x1c d", "en", "src2")]
    rows += [(305, "aaaa " * 300, "en", "src3"), (306, "é" * 120 + "x" + "é" * 120, "en", "src3"), (307, text(6000), "en", "src3"), (308, "a b " * 400 + shared, "en", "src3")]
    return [(*r, len(r[1] or ""), 0.5, "x") for r in rows]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(corpus(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def brute_suffix(rows, length=100):
    seen, out = set(), {}
    for doc, text in sorted((r[0], (r[1] or "").encode()) for r in rows):
        keep = bytearray(b"\1" * len(text))
        for p in range(len(text) - length + 1):
            window = text[p : p + length]
            if window in seen:
                keep[p : p + length] = b"\0" * length
            seen.add(window)
        left = bytes(c for c, k in zip(text, keep) if k)
        spans = sum(1 for i, k in enumerate(keep) if not k and (i == 0 or keep[i - 1]))
        out[doc] = (len(text), len(text) - len(left), spans, hashlib.sha256(left).hexdigest())
    return out


@pytest.mark.parametrize("hot", [4096, 2])
def test_suffix_dedup(docs, hot, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT_CONTENTS", hot)
    found = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.deduplicate(docs).collect()}
    assert found == brute_suffix(corpus())


def test_run_length_index_statistics():
    strings = [b"banana bandana banana", b"bandana banana", b"xx", b""]
    index = suffix_dedup.RunLengthIndex(strings)
    assert index.run_length.sum() == index.n
    neighbour, shared = index.matching_statistics()
    joined = b"\0".join(strings) + b"\0"
    for p in range(index.n):
        want = 0
        if neighbour[p] >= 0 and joined[p]:
            while joined[p + want] and joined[p + want] == joined[neighbour[p] + want]:
                want += 1
        assert shared[p] == want


def test_suffix_long_text_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "PIECE_BYTES", 700)
    monkeypatch.setattr(suffix_dedup, "BLOCK_BYTES", 300)
    found = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.deduplicate(spark.createDataFrame(corpus(), SCHEMA)).collect()}
    assert found == brute_suffix(corpus())


def simhash(text):
    w = words(lower(text))
    grams = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash(docs):
    rows = [(r[0], simhash(r[1])) for r in corpus()]
    parent = {d: d for d, _ in rows}
    changed = True
    while changed:
        changed = False
        for a, x in rows:
            for b, y in rows:
                if (x ^ y).bit_count() <= 3 and parent[a] > parent[b]:
                    parent[a], changed = parent[b], True
    found = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash_dedup.components(docs).collect()}
    assert found == {d: (f"{x:016x}", parent[d]) for d, x in rows}


def test_gray_index_finds_all_within_radius():
    rng = np.random.default_rng(0)
    base = rng.integers(0, 2**63, 200, dtype=np.uint64)
    near = base ^ (np.uint64(1) << rng.integers(0, 64, 200, dtype=np.uint64))
    codes = np.unique(np.concatenate([base, near, near ^ np.uint64(7)]))
    want = {(j, i) for i in range(len(codes)) for j in range(i) if int(codes[i] ^ codes[j]).bit_count() <= 3}
    pairs = lambda found: [(int(a), int(b)) for x, y in found for a, b in zip(x, y)]
    index = simhash_dedup.GrayHammingIndex(codes[:, None], fanout=4)
    got = pairs(index.links(3))
    assert {tuple(sorted(p)) for p in got} == want and len(got) == len(want)
    asked = pairs(index.links(3, codes[:50, None]))
    assert set(asked) == {(i, j) for i in range(50) for j in range(len(codes)) if int(codes[i] ^ codes[j]).bit_count() <= 3}


def test_gray_rank_of_wide_codes():
    rank = lambda x: simhash_dedup.gray_rank(np.array([[x >> 64, x & (1 << 64) - 1]], dtype=np.uint64))[0]
    for n in (0, 1, 5, (1 << 64) - 1, 1 << 64, (1 << 64) + 12345, (1 << 128) - 1):
        high, low = rank(n ^ n >> 1).tolist()
        assert high << 64 | low == n


def test_exact_tables_lose_no_pair():
    rng = np.random.default_rng(4)
    for n_codes, n_tables in ((100, 1), (1 << 20, 4), (1 << 33, 10), (1 << 40, 20)):
        tables = simhash_dedup.exact_tables(n_codes)
        assert len(tables.orders) == n_tables
        for _ in range(200):
            a = rng.integers(0, 2**63, (1, 1), dtype=np.uint64)
            b = a ^ np.bitwise_or.reduce(np.uint64(1) << rng.choice(64, 3, replace=False).astype(np.uint64))
            lead = lambda t, x: int(tables.turned(t, x)[0, 0]) >> 64 - tables.lead if tables.lead else 0  # noqa: B023, E731
            assert any(lead(t, a) == lead(t, b) for t in range(n_tables))


def test_full_slices_are_cut_along_the_gray_order(spark, monkeypatch):
    monkeypatch.setattr(simhash_dedup, "MEMBERS", 40)
    rng = random.Random(2)
    codes = {rng.getrandbits(12) << 40 | rng.getrandbits(40) & 0x3F for _ in range(1500)}
    rows = spark.createDataFrame([(c,) for c in codes], "code long")
    want = {frozenset(x) for x in groups_of(codes)}
    found: dict = {}
    for r in simhash_dedup.link_fingerprints(rows).collect():
        found.setdefault(r.root, set()).add(r.node)
    assert {frozenset(x) for x in found.values()} == {x for x in want if len(x) > 1}


def groups_of(codes, radius=3):
    left, out = set(codes), []
    while left:
        group, queue = set(), [left.pop()]
        while queue:
            a = queue.pop()
            group.add(a)
            near = {b for b in left if (a ^ b).bit_count() <= radius}
            left -= near
            queue += near
        out.append(group)
    return out


def test_components(spark):
    edges = [(i, i + 1) for i in range(50)] + [(100, 103), (103, 101), (7, 7)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(51)} | {100: 100, 101: 100, 103: 100}


def test_quality_rules(docs):
    found = {r.doc_id: r for r in quality_rules.judge(docs).collect()}
    for doc, text, *_ in corpus():
        w, r = words(text), found[doc]
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        often = Counter(grams)
        inside = {i + j for i, g in enumerate(grams) if often[g] > 1 for j in range(5)}
        lines = [x for x in (text or "").split("\n") if words(x)]
        assert (r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines) == (len(w), sum(map(len, w)), len(inside), len(lines) - len(set(lines)))
        assert r.n_symbols == sum(c in "#*$%&|<>" for c in text or "")
        assert r.base_failed == (len(w) < 10 or 100 * len(inside) > 20 * len(w))


def test_boilerplate_lines_go(spark):
    rows = [(i, f"Common  LINE number 7 here\nown words of document {' '.join(chr(97 + i % 26) * (1 + i // 26) + chr(97 + j % 26) * (1 + j // 26) for j in range(30))}", "en", "h", 0, 0.0, "x") for i in range(60)]
    rows.append((99, "common line number 3 here\n" * 4 + "one two three", "en", "h", 0, 0.0, "x"))
    frame = spark.createDataFrame(rows, SCHEMA)
    verdict = {r.doc_id: r for r in quality_rules.judge(frame).collect()}
    assert verdict[0].kept and verdict[0].removed_words == 5 and not verdict[99].kept
    kept = quality_rules.clean(frame)
    assert kept.columns == frame.columns and kept.where("lower(text) like '%common%'").isEmpty() and kept.count() == 60


def test_mixing(docs):
    rows = mixing.mix(docs).collect()
    total, sizes = 0, {}
    for r in rows:
        assert 0 <= r.taken <= 3 * r["size"]
        total += r["size"]
        sizes.setdefault(r.source, [0, r.target, 0])
        sizes[r.source][0] += r["size"]
        sizes[r.source][2] += r.taken
    names = sorted((s for s in sizes if s is not None)) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    capped: set = set()
    while True:
        left = total - sum(3 * sizes[s][0] for s in capped)
        rest = sum(weight[s] for s in names if s not in capped)
        over = {s for s in names if s not in capped and left * weight[s] / rest > 3 * sizes[s][0]}
        if not over:
            break
        capped |= over
    for s in names:
        target = 3 * sizes[s][0] if s in capped else left * weight[s] / rest
        assert math.isclose(sizes[s][1], target) and sizes[s][2] == math.floor(sizes[s][1] + 1e-9)
    copied = mixing.mixed_corpus(docs)
    assert copied.columns == docs.columns
    assert sum(len(words(r.text)) for r in copied.collect()) == sum(r.taken for r in rows)


def test_packing(docs):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(packing.vocabulary())
    rows = packing.pack(docs, keep_ids=True).collect()
    want = {d: tokenizer.encode(t or "", add_special_tokens=False).ids + [2] for d, t, *_ in corpus()}
    got, windows = {}, {}
    for r in sorted(rows, key=lambda r: (r.doc_id, r.start)):
        ids = np.frombuffer(r.ids, dtype="<u4").tolist()
        assert r.start == len(got.setdefault(r.doc_id, [])) and r.length == len(ids) and r.ids_crc32 == zlib.crc32(r.ids)
        got[r.doc_id] += ids
        windows.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert got == want
    for pieces in windows.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 4096


def test_word_cache_on_hard_texts():
    cache = packing.WordCache(packing.vocabulary())
    texts = ["", " a  b", "Héllo WORLD's it's ' we're \t\x0b x\x85y 　z", "ΑΣ Σ. ΑΣ,", "ﬁ é <|endoftext|>a foo.. bar,. a.b I'LL DON'T 12,3. x\x1cy İ ß.", "a\r\nb . , ÀÉ×÷ÿ, Été. ÀB", None]
    for chunk in chunks(pa.array(texts, pa.string())):
        ids, count = cache.encode(chunk)
    want = [cache.tokenizer.encode(t or "", add_special_tokens=False).ids for t in texts]
    assert [x.tolist() for x in np.split(ids, np.cumsum(count)[:-1])] == want


def test_chat_trees_choose_best_branch(spark):
    rows = [("r", None, "user", "q", None), ("a", "r", "assistant", "short", 1.0), ("b", "r", "assistant", "<|turn|> \\ [INST] better", 5.0), ("c", "b", "user", None, None), ("z", "lost", "user", "root of its own", None)]
    trees = chat_format.format_trees(spark.createDataFrame(rows, "node string, parent string, role string, text string, score double"), 1)
    got = {r.root: chat_format.read_back(r.formatted) for r in trees.collect()}
    assert got == {"r": [("user", "q"), ("assistant", "<|turn|> \\ [INST] better"), ("user", "")], "z": [("user", "root of its own")]}


def test_chat_deep_chain_and_ties(spark):
    rows = [(1, i, "user" if i % 2 else "assistant", f"t{i}") for i in range(70)] + [(1, 5, "user", "again"), (None, 0, None, None), (2, 0, "system", "x")]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.conversation: r.n_turns for r in chat_format.format_table(frame).collect()}
    assert got == {1: 71, None: 1, 2: 1}


def test_language_id(spark, middle):
    docs = spark.read.parquet(f"{middle}/documents.parquet")
    network = byte_cnn.fit(docs.where(~byte_cnn.held_out(4, 2)))
    judged = byte_cnn.identify(docs, network).join(docs.select("doc_id", "lang"), "doc_id")
    accuracy = judged.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert accuracy > 0.97
    odd = spark.createDataFrame([(1, None), (2, "123 !!"), (None, "été 日本")], "doc_id long, text string")
    assert [r.lang_pred for r in byte_cnn.identify(odd, network).orderBy("doc_id").collect()][1:] == ["und", "und"]


def test_language_tables_equal_convolution():
    network = byte_cnn.ByteNetwork(["a", "b"])
    x = np.random.default_rng(1).integers(0, 256, (5, 40)).astype(np.uint8)
    top, p = [], network.weights
    for w in byte_cnn.WIDTHS:
        seen = p["embed"][x]
        full = sum(seen[:, j : 40 - w + 1 + j] @ p[f"conv{w}"][j] for j in range(w)) + p[f"bias{w}"]
        top.append(full.max(axis=1))
    want = np.maximum(np.concatenate(top, axis=1), 0) @ p["out"] + p["out_bias"]
    assert np.allclose(network.logits(x), want, atol=1e-4)


def test_language_model(docs):
    rows = {r.doc_id: r for r in context_mixing.score(docs, head=20).collect()}
    tokens = lambda text: words(lower(text)) + [""]
    counts = Counter(t for d, text, *_ in corpus() if zlib.crc32(str(d).encode()) % 10 for t in tokens(text))
    n, v = sum(counts.values()), len(counts)
    for doc, text, *_ in corpus():
        r, own = rows[doc], tokens(text)
        base = sum(math.log10((counts[t] + 0.1) / (n + 0.1 * (v + 1))) for t in own)
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(own), sum(t in counts for t in own), n)
        assert math.isclose(r.base_score, base, rel_tol=1e-9) and r.score < 0
        assert math.isclose(r.bits_per_byte, -r.score / math.log10(2) / max(len((text or "").encode()), 1), rel_tol=1e-9)


def test_language_model_beats_its_base(spark, middle):
    """Held-out texts: the model's total is above the base's, and a text of letters costs less than four bits a byte."""
    rows = context_mixing.score(spark.read.parquet(f"{middle}/documents.parquet")).where("held_out")
    total = rows.agg(F.sum("score"), F.sum("base_score"), F.avg("bits_per_byte")).first()
    assert total[0] > total[1] and total[2] < 4


def test_other_labels_are_a_class_of_their_own(spark):
    rows = [(i, "x", f"l{i % 7}") for i in range(100)] + [(i, "x", None) for i in range(100, 130)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    number, n = context_mixing.text_classes(docs, "lang")
    assert n == 5 and {r[0] for r in docs.select(number).distinct().collect()} == set(range(5))
    number, n = context_mixing.text_classes(docs.where("lang in ('l0', 'l1')"), "lang")
    assert n == 2


def test_spelling_is_a_distribution():
    """One step's probabilities over all bytes and the end add up to one."""
    predictors = context_mixing.Predictors()
    predictors.learn(pa.array(["ab", "ac", "b"]), np.array([3, 2, 1]))
    mixer = context_mixing.Mixer(predictors.ones, predictors.all)
    total = 0.0
    for value in range(256):
        spelled = bytes([value])
        word, depth, bit, slots = context_mixing.events(np.frombuffer(spelled, dtype=np.uint8), np.array([0, 1]))
        p, _ = mixer.predict(*mixer.inputs(depth, slots))
        first = context_mixing.CODE_SIZE[value]
        total += np.prod(np.where(bit == 1, p, 1 - p)[:first])
    assert abs(total - 1) < 1e-9


def test_cap_filters(spark):
    rng = np.random.default_rng(5)
    base = rng.standard_normal((150, 16))
    near = base[:60] + 0.15 * rng.standard_normal((60, 16))
    values = [*base, *near, *base[:10], *base[:1].repeat(30, axis=0)]
    rows = [(i, [float(np.float32(x)) for x in v], i % 2 if i < 150 else (i - 150) % 2) for i, v in enumerate(values)]
    rows += [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] * 16, 0), (903, [1.0] * 16, None), (904, [], 1), (905, [1.0, None] * 8, 0), (906, [1.0, 2.0], 1)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    unit = {i: np.array(v) / np.linalg.norm(v) for i, v, _ in rows if i < 900}
    label = {i: lab for i, _, lab in rows}
    want = {i: sorted(j for j in unit if j != i and label[i] == label[j] and unit[i] @ unit[j] >= 0.93) for i in unit}
    got = {r.vec_id: r for r in cap_filters.link_vectors(frame).collect()}
    assert len(got) == len(rows)
    found, all_links = sum(got[i].n_links for i in want), sum(map(len, want.values()))
    assert 0.98 * all_links <= found <= all_links and all(got[i].n_links <= len(want[i]) for i in want)
    assert all(got[i].n_links == 0 and got[i].component_id == i and got[i].kept for i in range(900, 907))


@pytest.mark.parametrize(("dimension", "scale", "kind"), [(2, 1e200, "double"), (1, 1.0, "float"), (3, 1e-200, "double"), (5, 1.0, "float"), (9, 1e300, "double")])
def test_cap_filters_in_few_dimensions_and_at_any_scale(spark, dimension, scale, kind):
    rng = np.random.default_rng(dimension)
    values = rng.standard_normal((400, dimension)) * scale
    rows = [(i, v.tolist(), i % 2) for i, v in enumerate(values)]
    frame = spark.createDataFrame(rows, f"vec_id long, embedding array<{kind}>, label int")
    unit = cap_filters.unit(np.array(frame.toPandas().sort_values("vec_id")["embedding"].tolist(), dtype=np.float64))
    same = np.arange(400)[:, None] % 2 == np.arange(400)[None, :] % 2
    want = ((unit @ unit.T >= 0.93) & same).sum(axis=1) - 1
    got = {r.vec_id: r.n_links for r in cap_filters.link_vectors(frame).collect()}
    assert 0.97 * want.sum() <= sum(got.values()) <= want.sum() and all(got[i] <= want[i] for i in got)


def test_full_caps_are_cut_into_tiles(spark, monkeypatch):
    monkeypatch.setattr(cap_filters, "SPLIT_ROWS", 30)
    rng = np.random.default_rng(8)
    values = rng.standard_normal(16) + 0.08 * rng.standard_normal((250, 16))
    unit = cap_filters.unit(values)
    want = (unit @ unit.T >= 0.93).sum(axis=1) - 1
    frame = spark.createDataFrame([(i, v.tolist(), 1) for i, v in enumerate(values)], "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: (r.n_links, r.component_id) for r in cap_filters.link_vectors(frame).collect()}
    assert want.min() > 100 and [got[i][0] for i in range(250)] == want.tolist() and {c for _, c in got.values()} == {0}


def test_filter_designs_keep_list_and_cap_sizes():
    for dimension in (1, 2, 3, 6, 16, 64, 300):
        for n in (1000, 10**6):
            design = cap_filters.suited(dimension, n)
            assert cap_filters.mean_list(design) < 60, design
    assert cap_filters.suited(64, 10**6).words ** 2 >= cap_filters.LIST * 10**6 / cap_filters.PER_CAP


def test_weak_labels(spark, middle):
    docs, labels = spark.read.parquet(f"{middle}/documents.parquet"), spark.read.parquet(f"{middle}/labels.parquet")
    rates = {r.quality: r.k for r in weak_labels.classify(docs).join(labels, "doc_id").groupBy("quality").agg(F.avg(F.col("kept").cast("double")).alias("k")).collect()}
    assert rates[1] > 0.97 and rates[0] < 0.2


def test_em_recovers_accuracies():
    rng = np.random.default_rng(2)
    truth = rng.random(20000) < 0.8
    votes = np.stack([np.where(rng.random(20000) < a, np.where(truth, 2, 1), np.where(truth, 1, 2)) for a in (0.95, 0.9, 0.97)], axis=1)
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    table, share = weak_labels.estimate(patterns, counts)
    assert abs(share - 0.8) < 0.03 and abs(table[2, 1, 2] - 0.97) < 0.03


def test_empty_tables(spark, empty):
    assert suffix_dedup.deduplicate(empty).isEmpty() and simhash_dedup.components(empty).isEmpty() and quality_rules.judge(empty).isEmpty()
    assert mixing.mix(empty).isEmpty() and packing.pack(empty).isEmpty() and weak_labels.classify(empty).isEmpty() and context_mixing.score(empty).isEmpty()
    assert byte_cnn.identify(empty, byte_cnn.fit(empty)).isEmpty()
    assert chat_format.format_table(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).isEmpty()
    assert cap_filters.link_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).isEmpty()
