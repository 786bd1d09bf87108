"""Language identification by a byte-level convolutional network in numpy.

Embedding of bytes, filters of several widths, ReLU, max pooling over a window, softmax. Training takes a bounded,
documented sample of labelled windows; prediction runs over every fixed-length window of every whole text. In prediction a
filter's response is a sum of table rows (one per byte pair or byte), which equals the convolution and needs no products.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.llm.textkit import TO_LOWER, as_bytes

WINDOW, EMBED, FILTERS, WIDTHS = 256, 8, 16, (2, 3, 4)
SAMPLE_DOCS, WINDOWS_PER_DOC, STEPS, BATCH, RATE, SEED = 4000, 3, 800, 64, 0.01, 7
CHUNK_WINDOWS = 256
SPACE = 32
_is_letter = np.zeros(256, dtype=bool)
_is_letter[65:91] = _is_letter[97:123] = True


def fold(data: np.ndarray) -> np.ndarray:
    """Lower case for A-Z and for the Latin-1 capitals that UTF-8 writes after byte C3."""
    out = TO_LOWER[data]
    if len(out) > 1:
        second = (data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97)
        out[1:] += (second * 32).astype(np.uint8)
    return out


class ByteNetwork:
    def __init__(self, labels: list[str], seed: int = SEED) -> None:
        rng = np.random.default_rng(seed)
        self.labels = labels
        self.weights = {"embed": rng.standard_normal((256, EMBED)) * 0.5}
        for w in WIDTHS:
            self.weights[f"conv{w}"] = rng.standard_normal((w, EMBED, FILTERS)) / np.sqrt(w * EMBED)
            self.weights[f"bias{w}"] = np.zeros(FILTERS)
        self.weights["out"] = rng.standard_normal((FILTERS * len(WIDTHS), len(labels))) * 0.1
        self.weights["out_bias"] = np.zeros(len(labels))
        self.tables: dict | None = None

    def _gradients(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
        p, n = self.weights, len(x)
        seen, pooled, places = p["embed"][x], [], {}
        for w in WIDTHS:
            stacked = np.concatenate([seen[:, j : x.shape[1] - w + 1 + j] for j in range(w)], axis=2)
            response = stacked @ p[f"conv{w}"].reshape(-1, FILTERS) + p[f"bias{w}"]
            places[w] = response.argmax(axis=1)
            pooled.append(np.take_along_axis(response, places[w][:, None, :], axis=1)[:, 0])
        top = np.concatenate(pooled, axis=1)
        hidden = np.maximum(top, 0)
        logits = hidden @ p["out"] + p["out_bias"]
        chance = np.exp(logits - logits.max(axis=1, keepdims=True))
        chance /= chance.sum(axis=1, keepdims=True)
        error = chance
        error[np.arange(n), y] -= 1
        error *= weight[:, None] / n
        grad = {"out": hidden.T @ error, "out_bias": error.sum(axis=0), "embed": np.zeros_like(p["embed"])}
        back = (error @ p["out"].T) * (top > 0)
        for k, w in enumerate(WIDTHS):
            g = back[:, k * FILTERS : (k + 1) * FILTERS]
            grad[f"bias{w}"] = g.sum(axis=0)
            grad[f"conv{w}"] = np.zeros_like(p[f"conv{w}"])
            for j in range(w):
                byte = np.take_along_axis(x, places[w] + j, axis=1)
                grad[f"conv{w}"][j] = np.einsum("nfe,nf->ef", p["embed"][byte], g)
                np.add.at(grad["embed"], byte.ravel(), (g[:, :, None] * p[f"conv{w}"][j].T[None]).reshape(-1, EMBED))
        return grad

    def train(self, windows: np.ndarray, labels: np.ndarray, steps: int = STEPS, seed: int = SEED) -> None:
        """Adam over shuffled batches; each batch is seen at a random length, so that short texts are learned, too."""
        rng = np.random.default_rng(seed)
        balance = len(labels) / np.maximum(1, np.bincount(labels, minlength=len(self.labels))) / len(self.labels)
        first = {k: np.zeros_like(v) for k, v in self.weights.items()}
        second = {k: np.zeros_like(v) for k, v in self.weights.items()}
        order = np.zeros(0, dtype=np.int64)
        for step in range(1, steps + 1):
            if len(order) < min(BATCH, len(windows)):
                order = rng.permutation(len(windows))
            rows, order = order[:BATCH], order[BATCH:]
            length = int(rng.choice((WINDOW // 8, WINDOW // 4, WINDOW // 2, WINDOW)))
            rate = RATE * (1 - step / (steps + 1)) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
            for k, g in self._gradients(windows[rows][:, :length], labels[rows], balance[labels[rows]]).items():
                first[k] = 0.9 * first[k] + 0.1 * g
                second[k] = 0.999 * second[k] + 0.001 * g * g
                self.weights[k] -= rate * first[k] / (np.sqrt(second[k]) + 1e-8)

    def _prepare(self) -> dict:
        """Responses of byte pairs and of single bytes, per width and place."""
        if self.tables is None:
            p, pair = self.weights, np.arange(65536)
            single = {w: [(p["embed"] @ p[f"conv{w}"][j]).astype(np.float32) for j in range(w)] for w in WIDTHS}
            self.tables = {w: [single[w][j][pair >> 8] + single[w][j + 1][pair & 255] for j in range(0, w - 1, 2)] + ([single[w][-1]] if w % 2 else []) for w in WIDTHS}
        return self.tables

    def logits(self, windows: np.ndarray) -> np.ndarray:
        tables, pooled = self._prepare(), []
        pair = (windows[:, :-1].astype(np.int32) << 8) | windows[:, 1:]
        for w in WIDTHS:
            span = windows.shape[1] - w + 1
            response = None
            for j, table in enumerate(tables[w]):
                at = pair[:, 2 * j : 2 * j + span] if len(table) == 65536 else windows[:, 2 * j : 2 * j + span]
                part = table.take(at, axis=0)
                response = part if response is None else np.add(response, part, out=response)
            pooled.append(response.max(axis=1) + self.weights[f"bias{w}"].astype(np.float32))
        hidden = np.maximum(np.concatenate(pooled, axis=1), 0)
        return hidden @ self.weights["out"] + self.weights["out_bias"]

    def predict(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Label number and probability for each text, over the mean of its windows weighted by their bytes."""
        data, offsets = as_bytes(column)
        size = np.diff(offsets)
        total = np.zeros((len(size), len(self.labels)))
        count = -(-size // WINDOW)
        owner = np.repeat(np.arange(len(size)), count)
        begin = np.repeat(offsets[:-1], count) + (np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)) * WINDOW
        length = np.minimum(WINDOW, offsets[owner + 1] - begin)
        for low in range(0, len(owner), CHUNK_WINDOWS):
            who, at, n = owner[low : low + CHUNK_WINDOWS], begin[low : low + CHUNK_WINDOWS], length[low : low + CHUNK_WINDOWS]
            piece = fold(data[at[0] : at[-1] + n[-1]])
            place = np.arange(WINDOW)[None, :]
            windows = piece[np.minimum((at - at[0])[:, None] + place, len(piece) - 1)]
            windows[place >= n[:, None]] = SPACE
            np.add.at(total, who, self.logits(windows) * n[:, None])
        mean = total / np.maximum(size, 1)[:, None]
        chance = np.exp(mean - mean.max(axis=1, keepdims=True))
        chance /= chance.sum(axis=1, keepdims=True)
        return chance.argmax(axis=1), chance.max(axis=1)


def has_letter(column: pa.Array) -> np.ndarray:
    data, offsets = as_bytes(column)
    seen = np.zeros(len(data) + 1, dtype=np.int64)
    np.cumsum(_is_letter[data], out=seen[1:])
    found = seen[offsets[1:]] > seen[offsets[:-1]]
    for i in np.flatnonzero(~found):
        found[i] = any(c.isalpha() for c in data[offsets[i] : offsets[i + 1]].tobytes().decode("utf-8", "replace"))
    return found


def held_out(modulus: int, remainder: int) -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % modulus == remainder, F.lit(False))


def training_windows(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> list:
    """At most sample_docs documents, those of the least id hash, as WINDOWS_PER_DOC windows of their texts each."""
    order = F.xxhash64(F.col("doc_id"), F.lit(SEED))
    ids = docs.select("doc_id", "lang", order.alias("order")).orderBy("order").limit(sample_docs)
    bound = ids.agg(F.max("order")).first()[0]
    if bound is None:
        return []
    places = [F.substring(F.col("text"), F.pmod(F.xxhash64("doc_id", F.lit(k)), F.greatest(F.lit(1), F.length("text") - WINDOW)).cast("int") + 1, F.lit(WINDOW)) for k in range(WINDOWS_PER_DOC)]
    rows = docs.where(order <= bound).where("text is not null").select("doc_id", "lang", F.array(*places).alias("parts"))
    return rows.orderBy("doc_id").limit(sample_docs).collect()


def fit(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> ByteNetwork | None:
    """A network trained on labelled rows of docs; None if there are none."""
    rows = training_windows(docs.where("lang is not null"), sample_docs)
    texts = [(part.encode(), r["lang"]) for r in rows for part in r["parts"] if part]
    if not texts:
        return None
    labels = sorted({lang for _, lang in texts})
    windows = np.full((len(texts), WINDOW), SPACE, dtype=np.uint8)
    for i, (part, _) in enumerate(texts):
        piece = fold(np.frombuffer(part[:WINDOW], dtype=np.uint8))
        windows[i, : len(piece)] = piece
    network = ByteNetwork(labels)
    network.train(windows, np.array([labels.index(lang) for _, lang in texts]))
    return network


def identify(docs: DataFrame, network: ByteNetwork | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score. A null text, a text without letters, and any text when there was nothing to
    learn from is `und` with score 0; repeated rows and null ids are rows like others; an empty table gives no row."""
    handle = docs.sparkSession.sparkContext.broadcast(network)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = handle.value
        for batch in batches:
            text = batch.column("text")
            known = has_letter(text) & (model is not None)
            best, chance = model.predict(text) if model is not None else (np.zeros(len(text), int), np.zeros(len(text)))
            names = np.array(model.labels if model is not None else ["und"], dtype=object)
            label, score = np.where(known, names[best], "und"), np.where(known, chance, 0.0)
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "held_out": batch.column("held_out"), "lang_pred": pa.array(label, type=pa.string()), "score": pa.array(score)})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(4, 2).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, fit(docs.where(~held_out(4, 2))))
