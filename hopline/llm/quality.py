"""Graded quality by ordinal cumulative-link regression on hashed text.

P(grade > k) = sigmoid(score - threshold_k) with one weight vector for all grades and ordered thresholds. Features:
presence of hashed words that at least ``MIN_DF`` training texts hold, scaled by how unevenly the grades use them, and root frequencies of hashed trigrams over
byte classes (letters, digits, blanks; other bytes stand for themselves), which see markup, tables and shouting. Grades come from labels: 0 toxic, 1 low quality, 2 good. Training is numpy on the driver, on a bounded
sample of labelled texts (``SAMPLE`` documents, ``SAMPLE_BYTES`` characters in all); scoring reads every byte of every text.

Defined cases: a null or blank text has no features and scores as such; labels with a null in id or grade are left
out; a document with several labels has its lowest grade; without labels every document gets null grades and is kept;
extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.llm.sampling import SLACK, distinct_draws, thinned
from hopline.llm.textvec import WordReader

SAMPLE, SAMPLE_BYTES, MIN_DF = 10_000, 100_000_000, 5
STYLE, WORDS = 4096, 1 << 20
STEPS, RATE, DECAY = 250, 0.05, 1e-3
GRADES = 3


def _classes() -> np.ndarray:
    table = np.arange(256, dtype=np.int64)
    table[97:123] = table[128:] = 97
    table[65:91], table[48:58], table[[9, 11, 12, 13]] = 65, 48, 32
    return table


def style(raw: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Root frequencies of hashed class trigrams."""
    out = np.zeros(STYLE)
    for at in range(0, max(len(raw) - 2, 0), 1 << 20):
        c = table[raw[at : at + (1 << 20) + 2]]
        out += np.bincount(((c[:-2] * 961 + c[1:-1] * 31 + c[2:]) * 40503 >> 4) & (STYLE - 1), minlength=STYLE)
    return np.sqrt(out / max(1.0, out.sum()))


def letter_reader() -> WordReader:
    """Words are runs of letters here: every other ASCII byte parts them."""
    reader = WordReader()
    reader.blank[:128] = [not chr(b).isalpha() for b in range(128)]
    return reader


def _rows(batch: pa.RecordBatch, reader: WordReader, table: np.ndarray):
    column = batch.column("text").cast(pa.large_string())
    ends = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    for k, words in reader.texts(column):
        yield k, (words >> np.uint64(44)).astype(np.int64), style(data[ends[k] : ends[k + 1]] if len(words) else data[:0], table)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    reader, table = letter_reader(), _classes()
    for batch in batches:
        words, ids, values = [], [], []
        for _, w, s in _rows(batch, reader, table):
            at = np.flatnonzero(s)
            words.append(np.unique(w).astype(np.int32)), ids.append(at.astype(np.int32)), values.append(s[at].astype(np.float32))
        yield pa.RecordBatch.from_arrays([batch.column("grade"), pa.array(words, pa.list_(pa.int32())), pa.array(ids, pa.list_(pa.int32())), pa.array(values, pa.list_(pa.float32()))], names=["grade", "words", "ids", "vals"])


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


def train(grades: list[int], words: list, ids: list, values: list) -> dict:
    """Full-batch Adam on the ordinal likelihood; thresholds stay ordered as a first one plus positive gaps."""
    df = np.bincount(np.concatenate([np.asarray(w, np.int64) for w in words]) if words else np.zeros(0, np.int64), minlength=WORDS)
    kept = np.flatnonzero(df >= MIN_DF)
    # A word counts by how far its share among the lower grades is from that among the higher ones, for either cut.
    y = np.array(grades)
    by_grade = np.stack([np.bincount(np.concatenate([np.asarray(w, np.int64) for w, g in zip(words, grades, strict=True) if g == k] or [np.zeros(0, np.int64)]), minlength=WORDS)[kept] for k in range(GRADES)])
    many, scale = np.bincount(y, minlength=GRADES), np.zeros(len(kept))
    for k in range(1, GRADES):
        low = np.log((by_grade[:k].sum(axis=0) + 1) / (many[:k].sum() + 2))
        scale = np.maximum(scale, np.abs(low - np.log((by_grade[k:].sum(axis=0) + 1) / (many[k:].sum() + 2))))
    place = np.full(WORDS, -1)
    place[kept] = STYLE + np.arange(len(kept))
    rows, cols, vals = [], [], []
    for k, (w, i, v) in enumerate(zip(words, ids, values, strict=True)):
        mine = place[np.asarray(w, np.int64)]
        mine = mine[mine >= 0]
        cols += [np.asarray(i, np.int64), mine]
        vals += [np.asarray(v, float) * 4, scale[mine - STYLE]]
        rows.append(np.full(len(i) + len(mine), k))
    row, col, val = np.concatenate(rows), np.concatenate(cols), np.concatenate(vals)
    n = STYLE + len(kept)
    x = np.zeros(n + GRADES - 1)
    x[n:] = [-1.0] + [0.5] * (GRADES - 2)
    m = v = np.zeros_like(x)
    for step in range(1, STEPS + 1):
        theta = x[n] + np.concatenate([[0.0], np.cumsum(np.exp(x[n + 1 :]))])
        score = np.bincount(row, x[col] * val, minlength=len(y))
        above = np.concatenate([np.ones((len(y), 1)), sigmoid(score[:, None] - theta), np.zeros((len(y), 1))], axis=1)
        slope = above * (1 - above)
        at = np.arange(len(y))
        p = np.maximum(above[at, y] - above[at, y + 1], 1e-9)
        upper, lower = slope[at, y] / p / len(y), slope[at, y + 1] / p / len(y)
        g = np.zeros_like(x)
        d = lower - upper  # of the negative log-likelihood by the score
        g[:n] = np.bincount(col, d[row] * val, minlength=n) + DECAY * x[:n]
        by_theta = np.array([upper[y == k + 1].sum() - lower[y == k].sum() for k in range(GRADES - 1)])
        g[n] = by_theta.sum()
        for k in range(1, GRADES - 1):
            g[n + k] = by_theta[k:].sum() * np.exp(x[n + k])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        x = x - RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-9)
    theta = x[n] + np.concatenate([[0.0], np.cumsum(np.exp(x[n + 1 :]))])
    return {"style": x[:STYLE] * 4, "kept": kept, "word": x[STYLE:n] * scale, "theta": theta}


def _score(model: dict | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader, table = letter_reader(), _classes()
        weight = np.zeros(WORDS)
        if model:
            weight[model["kept"]] = model["word"]
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                tails = []
                for _, w, s in _rows(part, reader, table):
                    if model is None:
                        tails.append([None] * (GRADES - 1))
                        continue
                    w = np.unique(w[weight[w] != 0])
                    tails.append(sigmoid(weight[w].sum() + s @ model["style"] - model["theta"]).tolist())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(tails, pa.list_(pa.float64()))], names=["doc_id", "tails"])

    return run


def sampled(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """(doc_id, grade, text): at most ``sample`` labelled documents, one row an id (its least text by hash), the first
    ``SAMPLE_BYTES // sample`` characters of each. Repeats in either table don't enlarge it."""
    known = labels.where("doc_id is not null and quality is not null and toxic is not null")
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 0, 1).otherwise(2)
    each = known.select("doc_id", grade.alias("grade"), F.xxhash64("doc_id", F.lit(13)).alias("draw"))
    total = distinct_draws(each.select("draw"), "draw")
    # A document with several labels has its lowest grade. SLACK times the sample is drawn: ids without a text fall out.
    picked = thinned(each, "draw", sample, total).groupBy("doc_id", "draw").agg(F.min("grade").alias("grade")).orderBy("draw").limit(SLACK * sample)
    text = docs.select("doc_id", F.substring("text", 1, SAMPLE_BYTES // max(1, sample)).alias("text"), F.xxhash64("text").alias("hash")).where("text is not null")
    joined = text.join(F.broadcast(picked), "doc_id")
    one = joined.groupBy("doc_id", "draw", "grade").agg(F.min_by("text", "hash").alias("text"))
    return one.orderBy("draw").limit(sample).select("doc_id", "grade", "text")


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> dict | None:
    text = sampled(docs, labels, sample).select("grade", "text")
    got = text.mapInArrow(_features, "grade int, words array<int>, ids array<int>, vals array<float>").collect()
    return train([r.grade for r in got], [r.words for r in got], [r.ids for r in got], [r.vals for r in got]) if len({r.grade for r in got}) > 1 else None


def grades(docs: DataFrame, model: dict | None, least: float = 0.5) -> DataFrame:
    """doc_id, expected_grade, p_above_0, p_above_1, keep: not toxic with at least ``least`` probability."""
    scored = docs.select("doc_id", "text").mapInArrow(_score(model), "doc_id long, tails array<double>")
    tail = [F.round(F.get("tails", F.lit(k)), 6) for k in range(GRADES - 1)]
    return scored.select("doc_id", F.round(sum(F.get("tails", F.lit(k)) for k in range(GRADES - 1)), 6).alias("expected_grade"), *[t.alias(f"p_above_{k}") for k, t in enumerate(tail)], (F.coalesce(tail[0], F.lit(1.0)) >= least).alias("keep"))
