"""Quality classifier from weak labels.

Overlapping heuristic labellers vote good, bad or nothing on every text. Expectation-maximisation on the counts of vote
patterns (a table whose size depends on the number of labellers only) estimates each labeller's accuracy and the share of
good texts; the posterior of each text then serves as a soft label for a hashed linear scorer over words and word shapes,
which judges every text. The scorer is fitted on a bounded sample: at most SAMPLE_DOCS documents, those of the least id hash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.llm.quality_rules import text_statistics
from floorwalk.llm.textkit import HASH_A, NEWLINE, chunks

SAMPLE_DOCS, WORD_BITS, SHAPE_BITS, EPOCHS, BATCH, RATE, SEED = 6000, 16, 10, 6, 128, 0.5, 11
ABSTAIN, BAD, GOOD = 0, 1, 2
KEEP, FEW_WORDS = 0.5, 10
# Labeller -> (measure, votes good at or below, votes bad above); a negative sign turns the measure round.
LABELLERS = {
    "long_enough": ("-n_words", -40.0, -1.0),
    "word_length_high": ("word_length", 9.0, 11.0),
    "word_length_low": ("-word_length", -3.2, -2.5),
    "few_symbols": ("symbols_per_word", 0.02, 0.10),
    "few_bars": ("bar_share", 0.02, 0.20),
    "few_marked_words": ("marked_share", 0.30, 0.60),
    "few_repeated_lines": ("dup_line_share", 0.05, 0.30),
    "few_repeated_words": ("repeat_share", 0.05, 0.20),
    "little_upper_case": ("upper_share", 0.15, 0.50),
    "sentences_end": ("-ended_line_share", -0.60, -0.20),
    "few_digits": ("digit_share", 0.05, 0.20),
    "few_exclamations": ("exclamations_per_word", 0.03, 0.30),
}
_class = np.zeros(256, dtype=np.uint8)  # 1 upper, 2 lower, 3 digit, 4 other ASCII mark, 5 beyond ASCII
_class[33:127] = 4
_class[65:91], _class[97:123], _class[48:58], _class[128:] = 1, 2, 3, 5


def measures(column: pa.Array) -> dict[str, np.ndarray]:
    stats = text_statistics(column)
    n = np.maximum(stats["n_words"], 1)
    out = {"n_words": stats["n_words"].astype(float), "word_length": stats["word_chars"] / n, "symbols_per_word": stats["n_symbols"] / n, "repeat_share": stats["n_repeat_words"] / n}
    lines = np.array([len(x) for x in stats["line_hash"]], dtype=float)
    out["dup_line_share"] = stats["n_dup_lines"] / np.maximum(lines, 1)
    upper, letters, digits, marks, ended, bars, marked = [], [], [], [], [], [], []
    for chunk in chunks(column):
        kind = _class[chunk.data]
        upper.append(chunk.count_bytes(kind == 1))
        letters.append(chunk.count_bytes((kind == 1) | (kind == 2)))
        digits.append(chunk.count_bytes(kind == 3))
        marks.append(chunk.count_bytes(chunk.data == ord("!")))
        start, end, doc = chunk.words()
        bars.append(chunk.per_doc(doc[(end - start == 1) & (kind[start] == 4)]))
        marked.append(chunk.per_doc(doc[kind[end - 1] == 4]))
        stop = np.zeros(len(chunk.data), dtype=bool)
        stop[:-1] = chunk.data[1:] == NEWLINE
        full = chunk.offsets[1:][np.diff(chunk.offsets) > 0] - 1
        stop[full] = True
        ended.append(chunk.count_bytes(stop & np.isin(chunk.data, np.frombuffer(b".!?\"')", dtype=np.uint8))))
    join = lambda x: np.concatenate(x).astype(float) if x else np.zeros(0)
    upper, letters, digits, marks, ended, bars, marked = map(join, (upper, letters, digits, marks, ended, bars, marked))
    out["bar_share"], out["marked_share"] = bars / n, marked / n
    out["upper_share"] = upper / np.maximum(letters, 1)
    out["digit_share"] = digits / np.maximum(letters + digits, 1)
    out["exclamations_per_word"] = marks / n
    out["ended_line_share"] = ended / np.maximum(lines, 1)
    return out


def votes(column: pa.Array) -> np.ndarray:
    """A row per text, a column per labeller. Shares in a text of a few words say little: no
    bad votes there. A text without words gets no votes."""
    found = measures(column)
    out = np.zeros((len(column), len(LABELLERS)), dtype=np.int64)
    for k, (name, good, bad) in enumerate(LABELLERS.values()):
        value = -found[name[1:]] if name[0] == "-" else found[name]
        out[:, k] = np.where(value <= good, GOOD, np.where(value > bad, BAD, ABSTAIN))
    out[(out == BAD) & (found["n_words"] < FEW_WORDS)[:, None]] = ABSTAIN
    out[found["n_words"] == 0] = ABSTAIN
    return out


def estimate(patterns: np.ndarray, counts: np.ndarray, rounds: int = 100) -> tuple[np.ndarray, float]:
    """Accuracy table [labeller, truth, vote] and share of good texts, by expectation-maximisation on vote patterns.

    Starts from the belief that a text with a bad vote is bad, as labellers look for different faults; abstaining
    says nothing.
    """
    n_labels = patterns.shape[1]
    lead = 2.0 - 4.0 * (patterns == BAD).sum(axis=1)
    belief = 1 / (1 + np.exp(-lead))
    table, share = np.full((n_labels, 2, 3), 1 / 3), 0.5
    if not counts.sum():
        return table, share
    for _ in range(rounds):
        share = float(np.clip((belief * counts).sum() / counts.sum(), 0.01, 0.99))
        for truth, weight in enumerate(((1 - belief) * counts, belief * counts)):
            for vote in (BAD, GOOD):
                table[:, truth, vote] = ((patterns == vote) * weight[:, None]).sum(axis=0) + 0.1
        table[:, :, ABSTAIN] = 0
        table /= table.sum(axis=2, keepdims=True)
        table[:, :, ABSTAIN] = 1
        new = posterior(patterns, table, share)
        if np.abs(new - belief).max() < 1e-9:
            break
        belief = new
    return table, share


def posterior(patterns: np.ndarray, table: np.ndarray, share: float) -> np.ndarray:
    odds = np.full(len(patterns), np.log(share / (1 - share)))
    for k in range(patterns.shape[1]):
        odds += np.log(table[k, 1, patterns[:, k]] / table[k, 0, patterns[:, k]])
    return 1 / (1 + np.exp(-np.clip(odds, -60, 60)))


def features(chunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number, hashed word and hashed shape of every word."""
    start, end, doc = chunk.words()
    word = (HASH_A.spans(HASH_A.prefix(chunk.data), start, end) >> np.uint64(64 - WORD_BITS)).astype(np.int64)
    kind, shape = _class[chunk.data], np.zeros(len(start), dtype=np.int64)
    for k in range(1, 6):
        seen = np.concatenate([[0], np.cumsum(kind == k)])
        shape |= (seen[end] > seen[start]).astype(np.int64) << (k - 1)
    shape |= np.minimum((end - start) >> 2, 7) << 5
    shape |= (kind[end - 1] == 4).astype(np.int64) << 8
    again = np.zeros(len(start), dtype=np.int64)
    again[1:] = (word[1:] == word[:-1]) & (doc[1:] == doc[:-1])
    shape |= again << 9
    return doc, word, (1 << WORD_BITS) + shape


class LinearScorer:
    def __init__(self) -> None:
        self.weights, self.bias = np.zeros((1 << WORD_BITS) + (1 << SHAPE_BITS)), 0.0

    def fit(self, rows: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, seed: int = SEED) -> None:
        """Logistic loss on soft labels, adaptive steps; a text's features are its relative frequencies, root-scaled."""
        rng, squares, bias_square = np.random.default_rng(seed), np.full(len(self.weights), 1e-6), 1e-6
        for _ in range(epochs):
            order = rng.permutation(len(rows))
            for low in range(0, len(order), BATCH):
                batch = order[low : low + BATCH]
                size = np.array([len(rows[i]) for i in batch])
                flat = np.concatenate([rows[i] for i in batch])
                owner = np.repeat(np.arange(len(batch)), size)
                total = np.bincount(owner, weights=self.weights[flat], minlength=len(batch)) / np.maximum(size, 1) + self.bias
                error = labels[batch] - 1 / (1 + np.exp(-np.clip(total, -60, 60)))
                step = np.bincount(flat, weights=(error / np.maximum(size, 1))[owner], minlength=len(self.weights))
                squares += step * step
                self.weights += RATE * step / np.sqrt(squares)
                bias_square += error.mean() ** 2
                self.bias += 0.1 * error.mean() / np.sqrt(bias_square)

    def score(self, column: pa.Array) -> np.ndarray:
        out = []
        for chunk in chunks(column):
            doc, word, shape = features(chunk)
            n = 2 * chunk.per_doc(doc)
            total = chunk.per_doc(doc, self.weights[word] + self.weights[shape]) / np.maximum(n, 1) + self.bias
            out.append(np.where(n > 0, 1 / (1 + np.exp(-np.clip(total, -60, 60))), 0.0))
        return np.concatenate(out) if out else np.zeros(0)


def _vote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    power = 3 ** np.arange(len(LABELLERS))
    for batch in batches:
        yield pa.RecordBatch.from_arrays([*batch.drop_columns(["text"]).columns, pa.array(votes(batch.column("text")) @ power)], names=["doc_id", "pattern"])


def _sample_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    power = 3 ** np.arange(len(LABELLERS))
    for batch in batches:
        text, found = batch.column("text"), []
        for chunk in chunks(text):
            doc, word, shape = features(chunk)
            cut = np.searchsorted(doc, np.arange(chunk.n_docs + 1))
            found += [np.concatenate([word[a:b], shape[a:b]]).astype(np.int32).tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]
        yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "pattern": pa.array(votes(text) @ power), "features": pa.array(found, pa.binary())})


def unpack(pattern: np.ndarray) -> np.ndarray:
    return (pattern[:, None] // 3 ** np.arange(len(LABELLERS))) % 3


def classify(docs: DataFrame, sample_docs: int = SAMPLE_DOCS, keep: float = KEEP) -> DataFrame:
    """doc_id, n_votes, posterior (of the labellers), score (of the scorer), kept.

    A null or wordless text has no votes, score 0 and is not kept; repeated rows and null ids are rows like others; an
    empty table gives no row; columns beyond doc_id and text are not read.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    counted = rows.mapInArrow(_vote, "doc_id long, pattern long").groupBy("pattern").count().toPandas()
    table, share = estimate(unpack(counted["pattern"].to_numpy(dtype=np.int64)), counted["count"].to_numpy(dtype=np.int64))
    order = F.xxhash64("doc_id", F.lit(SEED))
    bound = rows.where("text is not null").select(order.alias("order")).orderBy("order").limit(sample_docs).agg(F.max("order")).first()[0]
    scorer = LinearScorer()
    if bound is not None:
        sample = rows.where("text is not null").where(order <= bound).mapInArrow(_sample_rows, "doc_id long, pattern long, features binary").orderBy("doc_id", "pattern").limit(sample_docs).toArrow()
        labels = posterior(unpack(sample["pattern"].to_numpy()), table, share)
        scorer.fit([np.frombuffer(f, dtype=np.int32) for f in sample["features"].to_pylist()], labels)
    handle = spark.sparkContext.broadcast((scorer, table, share))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, accuracy, good = handle.value
        for batch in batches:
            text = batch.column("text")
            vote = votes(text)
            score = model.score(text)
            yield pa.RecordBatch.from_pydict({
                "doc_id": batch.column("doc_id"), "n_votes": pa.array((vote != ABSTAIN).sum(axis=1)),
                "posterior": pa.array(posterior(vote, accuracy, good)), "score": pa.array(score), "kept": pa.array(score >= keep),
            })

    return rows.mapInArrow(run, "doc_id long, n_votes long, posterior double, score double, kept boolean")


def query(spark, sf_dir: str) -> DataFrame:
    return classify(spark.read.parquet(f"{sf_dir}/documents.parquet"))
