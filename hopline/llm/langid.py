"""Language of whole texts by a convolutional network over bytes.

Bytes (A-Z lower-cased) are embedded, convolved with filters of widths 2, 3 and 4, max-pooled over a window of
``WINDOW`` bytes and classified by softmax. Training is numpy on the driver, on a bounded sample of labelled texts
(``SAMPLE`` windows of distinct texts, chosen by a hash of the text). Prediction covers every byte of every text:
the text is cut into windows, and the window's log-probabilities are averaged. As inputs are bytes, each filter is a
sum of table look-ups over byte pairs, which replaces the matrix product of the convolution.

Defined cases: a text that is null or without letters gets ``und`` with score 0; repeated rows get equal results;
without any labelled training text every document gets ``und``; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructType

from hopline.llm.sampling import distinct_draws, thinned

WINDOW, SAMPLE = 256, 6000
WIDTHS, FILTERS, DIM = (2, 3, 4), 10, 8
EPOCHS, LEAST_STEPS, BATCH, RATE = 4, 300, 64, 0.01
UNDETERMINED = "und"


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")), F.lit(3)) == 1, F.lit(False))


def _fold() -> np.ndarray:
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    return table


def train(windows: list[bytes], labels: list[str], seed: int = 11) -> dict:
    """Adam on cross-entropy; the gradient flows through the position that each filter's maximum came from."""
    rng, names = np.random.default_rng(seed), sorted(set(labels))
    x = np.zeros((len(windows), WINDOW), np.uint8)
    for k, w in enumerate(windows):
        part = np.frombuffer(w[:WINDOW], np.uint8)
        x[k, : len(part)] = part
    x, y = _fold()[x], np.array([names.index(v) for v in labels])
    p = {"emb": rng.normal(0, 0.5, (256, DIM)), "out": rng.normal(0, 0.1, (len(WIDTHS) * FILTERS, len(names))), "bias": np.zeros(len(names))}
    p |= {f"w{w}": rng.normal(0, 1 / np.sqrt(w * DIM), (w * DIM, FILTERS)) for w in WIDTHS} | {f"b{w}": np.zeros(FILTERS) for w in WIDTHS}
    p = {k: v.astype(np.float32) for k, v in p.items()}
    m, v = ({k: np.zeros_like(a) for k, a in p.items()} for _ in range(2))
    step = 0
    for _ in range(max(EPOCHS, -(-LEAST_STEPS * BATCH // len(x)))):
        order = rng.permutation(len(x))
        for at in range(0, len(x), BATCH):
            xb, yb = x[order[at : at + BATCH]], y[order[at : at + BATCH]]
            e, pooled, places = p["emb"][xb], [], []
            for w in WIDTHS:
                cols = np.concatenate([e[:, k : WINDOW - w + 1 + k] for k in range(w)], axis=2)
                act = cols @ p[f"w{w}"] + p[f"b{w}"]
                where = act.argmax(axis=1)
                places.append((cols, where))
                pooled.append(np.maximum(np.take_along_axis(act, where[:, None], 1)[:, 0], 0))
            h = np.concatenate(pooled, axis=1)
            z = h @ p["out"] + p["bias"]
            prob = np.exp(z - z.max(axis=1, keepdims=True))
            prob /= prob.sum(axis=1, keepdims=True)
            dz = prob.copy()
            dz[np.arange(len(yb)), yb] -= 1
            dz /= len(yb)
            g = {"out": h.T @ dz, "bias": dz.sum(axis=0), "emb": np.zeros_like(p["emb"])}
            dh = (dz @ p["out"].T) * (h > 0)
            for i, w in enumerate(WIDTHS):
                cols, where = places[i]
                d = dh[:, i * FILTERS : (i + 1) * FILTERS]
                patch = cols[np.arange(len(yb))[:, None], where]
                g[f"w{w}"], g[f"b{w}"] = np.einsum("bfc,bf->cf", patch, d), d.sum(axis=0)
                back = (d[:, :, None] * p[f"w{w}"].T[None]).reshape(len(yb), FILTERS, w, DIM)
                at_byte = xb[np.arange(len(yb))[:, None, None], where[:, :, None] + np.arange(w)]
                np.add.at(g["emb"], at_byte, back)
            step += 1
            for k in p:
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                p[k] -= RATE * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
                p[k] = p[k].astype(np.float32)
    return {"names": names, "params": p}


class Network:
    def __init__(self, model: dict):
        p, self.names = model["params"], model["names"]
        pos = {w: [p["emb"] @ p[f"w{w}"][k * DIM : (k + 1) * DIM] for k in range(w)] for w in WIDTHS}  # [256, FILTERS] for each place
        pair = lambda a, b: (a[:, None] + b[None]).reshape(65536, FILTERS)
        self.first = np.concatenate([pair(pos[w][0], pos[w][1]) for w in WIDTHS], axis=1).astype(np.float32)
        self.third, self.last = pos[3][2].astype(np.float32), pair(pos[4][2], pos[4][3]).astype(np.float32)
        self.bias = np.concatenate([p[f"b{w}"] for w in WIDTHS])
        self.out, self.out_bias, self.fold = p["out"], p["bias"], _fold()

    def log_probabilities(self, x: np.ndarray) -> np.ndarray:
        """x: [windows, WINDOW] bytes; zero bytes fill up the last window of a text."""
        x = self.fold[x].astype(np.int32)
        two = (x[:, :-1] << 8) | x[:, 1:]
        act = self.first.take(two, axis=0)
        act[:, :-1, FILTERS : 2 * FILTERS] += self.third.take(x[:, 2:], axis=0)
        act[:, :-2, 2 * FILTERS :] += self.last.take(two[:, 2:], axis=0)
        act[:, -1, FILTERS:] = act[:, -2, 2 * FILTERS :] = -np.inf
        h = np.maximum(act.max(axis=1) + self.bias, 0)
        z = h @ self.out + self.out_bias
        z -= z.max(axis=1, keepdims=True)
        return z - np.log(np.exp(z).sum(axis=1, keepdims=True))

    def texts(self, raws: list[bytes]) -> tuple[list[str], list[float]]:
        many = [max(1, -(-len(r) // WINDOW)) for r in raws]
        total = np.zeros((len(raws), len(self.names)))
        owner = np.repeat(np.arange(len(raws)), many)
        data = np.frombuffer(b"".join(r.ljust(n * WINDOW, b"\0") for r, n in zip(raws, many, strict=True)), np.uint8).reshape(-1, WINDOW)
        for at in range(0, len(data), 64):
            np.add.at(total, owner[at : at + 64], self.log_probabilities(data[at : at + 64]))
        total /= np.array(many)[:, None]
        prob = np.exp(total - total.max(axis=1, keepdims=True))
        prob /= prob.sum(axis=1, keepdims=True)
        best = prob.argmax(axis=1)
        return [self.names[b] for b in best], prob[np.arange(len(raws)), best].tolist()


def fit(docs: DataFrame, sample: int = SAMPLE) -> dict | None:
    """Trains on texts outside the held-out third; texts are drawn by their own hash, one window each."""
    rows = docs.where(F.col("text").isNotNull() & F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    draw = F.xxhash64("text", F.lit(5))
    at = F.pmod(F.xxhash64("text", F.lit(6)), F.greatest(F.lit(1), F.length("text") - WINDOW)) + 1
    total = distinct_draws(rows.select(draw.alias("draw")), "draw")
    drawn = thinned(rows.select(draw.alias("draw"), "lang", "text", at.alias("at")), "draw", sample, total)
    picked = drawn.select("draw", "lang", F.substring(F.col("text"), F.col("at").cast("int"), F.lit(WINDOW)).alias("part"))
    got = picked.groupBy("draw").agg(F.min_by("lang", F.struct("lang", "part")).alias("lang"), F.min("part").alias("part")).orderBy("draw").limit(sample).collect() if sample else []
    return train([r.part.encode() for r in got], [r.lang for r in got]) if got else None


def _predict(model: dict | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        network = Network(model) if model else None
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                ok = [a and network is not None for a in part.column("letters").to_pylist()]
                text = part.column("text") if "text" in part.schema.names else part.column("row").field("text")
                raws = text.cast(pa.large_binary()).to_pylist()
                lang, score = [UNDETERMINED] * len(ok), [0.0] * len(ok)
                index = [k for k, good in enumerate(ok) if good]
                if index:
                    for k, a, b in zip(index, *network.texts([raws[k] for k in index]), strict=True):
                        lang[k], score[k] = a, b
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in range(part.num_columns - 1)), pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*part.schema.names[:-1], "lang_pred", "score"])

    return run


def _predicted(row: DataFrame, model: dict | None) -> DataFrame:
    """Adds lang_pred and score to rows whose last column is ``letters``; the text is a column or lies in ``row``."""
    schema = StructType(row.schema.fields[:-1]).add("lang_pred", StringType()).add("score", DoubleType())
    return row.mapInArrow(_predict(model), schema)


def has_letters(text: Column) -> Column:
    return F.coalesce(text.rlike(r"\p{L}"), F.lit(False)).alias("letters")


def identify(docs: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, lang_pred, score."""
    row = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text", has_letters(F.col("text")))
    return _predicted(row, fit(docs, sample)).drop("text")


def keep_identified(docs: DataFrame, least: float = 0.3) -> DataFrame:
    """Documents whose language is found with at least ``least`` probability."""
    row = docs.select(F.struct("*").alias("row"), has_letters(F.col("text")))
    return _predicted(row, fit(docs)).where((F.col("lang_pred") != UNDETERMINED) & (F.col("score") >= least)).select("row.*")
