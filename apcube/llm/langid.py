"""Language identification: averaged hashed subword embeddings, a linear softmax, SGD in numpy, calibrated rejection.

Training reads a bounded sample of labelled rows (``per_lang`` documents and ``lang_bytes`` bytes of a language in
expectation; whole texts). A document is the mean of the embeddings of its hashed byte 3- and 4-grams. As everything
after the mean is linear, prediction gathers rows of one small table (embeddings times weights), so its cost per
n-gram doesn't depend on the embedding's width. A part of the sample that training doesn't see sets the softmax
temperature and the score below which a document is rejected.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from apcube.llm.wordhash import _SPACE, _TABLE, slices, text_buffers

GRAMS = (3, 4)
UNDETERMINED = "und"
_FOLD = _TABLE.copy()
_FOLD[_SPACE] = 32


def _grams(data: np.ndarray, offsets: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all n-grams, document by document, and their bounds. Each text is set between two blanks."""
    base = int(offsets[0])
    data, offsets = data[base : int(offsets[-1])], offsets.astype(np.int64) - base
    docs = len(offsets) - 1
    padded = np.full(len(data) + 2 * docs, 32, np.uint8)
    padded[np.arange(len(data)) + np.repeat(2 * np.arange(docs) + 1, np.diff(offsets))] = _FOLD[data]
    begin = offsets + 2 * np.arange(docs + 1)
    x = padded.astype(np.uint32)
    out, count = [], np.zeros(docs, np.int64)
    key = np.zeros(len(x), np.uint32)
    ends = np.repeat(begin[1:], np.diff(begin))
    index = np.arange(len(x))
    for n in range(1, max(GRAMS) + 1):
        key[: len(x) - n + 1] |= x[n - 1 :] << np.uint32(8 * (n - 1))
        if n in GRAMS:
            ok = index + n <= ends
            h = (key * np.uint32(2654435761) ^ (key >> np.uint32(15)) * np.uint32(2246822519 + 2 * n)) * np.uint32(3266489917)
            out.append((h >> np.uint32(32 - bits))[ok])
            count += np.maximum(np.diff(begin) - n + 1, 0)
    # documents stay together: each family of n-grams is in order, so a document's share of each is a range
    per = [np.maximum(np.diff(begin) - n + 1, 0) for n in GRAMS]
    bounds = np.concatenate([[0], np.cumsum(count)])
    merged = np.empty(int(bounds[-1]), np.uint32)
    shift = np.zeros(docs, np.int64)
    for values, mine in zip(out, per):
        first = np.concatenate([[0], np.cumsum(mine)])[:-1]
        merged[np.arange(len(values)) + np.repeat(bounds[:-1] + shift - first, mine)] = values
        shift += mine
    return merged, bounds


@dataclass
class Model:
    langs: list[str]
    table: np.ndarray = field(repr=False)  # buckets x languages: embeddings times weights
    bias: np.ndarray = field(repr=False)
    temperature: float = 1.0
    reject_below: float = 0.0
    bits: int = 16

    def logits(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        ids, bounds = _grams(data, offsets, self.bits)
        n = np.diff(bounds)
        out = np.zeros((len(n), len(self.langs)))
        full = np.flatnonzero(n)
        if len(full):
            for c in range(len(self.langs)):
                out[full, c] = np.add.reduceat(self.table[:, c][ids], bounds[:-1][full]) / n[full]
        return out + self.bias

    def scores(self, logits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        z = logits / self.temperature
        z -= z.max(axis=1, keepdims=True)
        p = np.exp(z)
        p /= p.sum(axis=1, keepdims=True)
        best = p.argmax(axis=1)
        return best, p[np.arange(len(p)), best]


def _sparse(texts: list[str], bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    out = []
    for t in texts:
        ids, _ = _grams(np.frombuffer(raw := t.encode(), np.uint8), np.array([0, len(raw)]), bits)
        u, c = np.unique(ids, return_counts=True)
        out.append((u, c / max(1, c.sum())))
    return out


def train(texts: list[str], labels: list[str], held: list[bool], bits: int = 16, width: int = 16, epochs: int = 12, rate: float = 4.0, reject_share: float = 0.002, seed: int = 3) -> Model:
    """Fits on the rows not ``held``; those held set the temperature and the rejection score, below which at most
    ``reject_share`` of the held rows whose language is predicted rightly would fall (never above 0.4)."""
    langs = sorted(set(labels))
    if not langs:
        return Model([], np.zeros((1 << bits, 0)), np.zeros(0), bits=bits)
    if len(set(x for x, h in zip(labels, held) if not h)) < len(langs):
        held = [False] * len(texts)  # too few rows to spare any
    g = np.random.default_rng(seed)
    emb, w, bias = g.normal(0, 0.3, (1 << bits, width)), np.zeros((width, len(langs))), np.zeros(len(langs))
    y = np.array([langs.index(x) for x in labels])
    docs = _sparse(texts, bits)
    rows = np.flatnonzero(~np.array(held))
    steps, at = epochs * len(rows), 0
    for _ in range(epochs):
        for i in g.permutation(rows):
            step = rate * (1 - at / steps)
            at += 1
            ids, share = docs[i]
            x = share @ emb[ids]
            z = x @ w + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1
            back = w @ p
            w -= step * np.outer(x, p)
            bias -= 0.01 * step * p
            emb[ids] -= step * share[:, None] * back
    model = Model(langs, emb @ w, bias, bits=bits)
    check = np.flatnonzero(held) if any(held) else rows
    logit = np.array([share @ model.table[ids] for ids, share in (docs[i] for i in check)]) + bias

    def loss(t: float) -> float:
        z = logit / t
        z -= z.max(axis=1, keepdims=True)
        return float((np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(check)), y[check]]).mean())

    model.temperature = float(min(2.0 ** np.arange(-3, 4.01, 0.25), key=loss))
    best, score = model.scores(logit)
    right = score[best == y[check]]
    model.reject_below = float(min(0.4, np.quantile(right, reject_share, method="lower"))) if len(right) else 0.0
    return model


def learn(docs: DataFrame, usable: Column, held: Column, per_lang: int = 1300, lang_bytes: int = 6 << 20, seed: int = 3, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """A model from rows where ``usable``; of each language about ``per_lang`` documents and at most ``lang_bytes`` bytes
    in expectation, chosen by a hash of the id; of those, rows where ``held`` calibrate. An executor trains; the driver gets
    the model alone."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang"), held.alias("held")).where(usable & F.col(lang_col).isNotNull() & F.col(text_col).rlike(r"\p{L}"))
    sizes = rows.groupBy("lang").agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("b")).collect()
    if not sizes:
        return train([], [], [])
    share = F.lit(0.0)
    for r in sizes:
        share = F.when(F.col("lang") == r["lang"], min(1.0, per_lang / r["n"], lang_bytes / max(1, r["b"]))).otherwise(share)
    unit = F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(1 << 20)) / float(1 << 20)

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sample = sorted((r for b in batches for r in b.to_pylist()), key=lambda r: (r["doc_id"] is None, r["doc_id"], r["text"]))
        model = train(*([f(r[c]) for r in sample] for c, f in (("text", str), ("lang", str), ("held", bool))))
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])

    # one task, as the sample is bounded: its texts and n-grams stay off the driver
    found = rows.where(unit < share).repartition(1).mapInArrow(fit, "model binary").first()
    return pickle.loads(found["model"]) if found else train([], [], [])


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", *keep: Column) -> DataFrame:
    """Per row: doc_id, the ``keep`` columns, lang_pred string, score double, rejected boolean.

    Texts that are null or hold no letter (empty ones too) and all texts under a model without languages are
    ``und`` with score 0 and rejected; others get their likeliest language however low its score, and are rejected below
    the model's threshold. Only the whole text decides. Rows of equal text get equal results.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)
    narrow = docs.select(F.col(id_col).alias("doc_id"), *keep, F.coalesce(F.col(text_col).cast("string").rlike(r"\p{L}"), F.lit(False)).alias("__letters"), F.col(text_col).cast("string").alias("text"))
    names = narrow.columns[:-2]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for part in slices(batches, "text", 1 << 20):
            ok = part.column("__letters").to_numpy(zero_copy_only=False).astype(bool)
            pred, score = np.full(part.num_rows, UNDETERMINED, object), np.zeros(part.num_rows)
            if m.langs and ok.any():
                best, value = m.scores(m.logits(*text_buffers(part.column("text"))))
                pred[ok], score[ok] = np.array(m.langs, object)[best][ok], value[ok]
            rejected = ~ok | (score < m.reject_below) | (not m.langs)
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array(pred, pa.string()), pa.array(score), pa.array(rejected)], [*names, "lang_pred", "score", "rejected"])

    head = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in narrow.schema.fields[:-2])
    return narrow.mapInArrow(run, f"{head}, lang_pred string, score double, rejected boolean")


def fold(id_col: str, n: int) -> Column:
    """crc32 of the id as text, modulo ``n``; null for a null id."""
    return F.crc32(F.col(id_col).cast("string")) % n


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **options) -> DataFrame:
    """Learns from rows of remainder 0 (training) and 2 (calibration) modulo 3 and predicts every row; ``held_out``
    marks remainder 1. A row without id is neither learned from nor held out."""
    rest = fold(id_col, 3)
    model = learn(docs, rest != 1, rest == 2, id_col=id_col, text_col=text_col, lang_col=lang_col, **options)
    return predict(docs, model, id_col, text_col, F.coalesce(rest == 1, F.lit(False)).alias("held_out"))


def keep_identified(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **options) -> DataFrame:
    """``docs``, all columns, without the rows that the model rejects; learned as in ``identify``."""
    rest = fold(id_col, 3)
    model = learn(docs, rest != 1, rest == 2, id_col=id_col, text_col=text_col, lang_col=lang_col, **options)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    marked = docs.withColumn("__letters", F.coalesce(F.col(text_col).cast("string").rlike(r"\p{L}"), F.lit(False)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for part in slices(batches, text_col, 1 << 20):
            ok = part.column("__letters").to_numpy(zero_copy_only=False).astype(bool) & bool(m.langs)
            if ok.any():
                ok &= m.scores(m.logits(*text_buffers(part.column(text_col))))[1] >= m.reject_below
            yield part.drop_columns(["__letters"]).filter(pa.array(ok))

    return marked.mapInArrow(run, docs.schema)
