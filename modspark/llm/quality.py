"""Quality classifier: support vectors over naive Bayes weighted n-grams.

A text's features are indicators of hashed byte n-grams of its lower-cased form and of its words' outlines. Each is scaled by
the log ratio of its smoothed frequencies in the two classes; a linear model with squared hinge loss is fitted on the scaled
rows by dual coordinate descent; a logistic curve over the margins of held-back training rows turns margins into scores, set so that
the stated threshold is the decision that balances the classes' errors.

The fit uses a bounded sample of labelled rows (``FIT_ROWS``, those with the least hash of their id) in one task; scoring covers
every row, whole, and the weights are one array of fixed length.

Defined results: a null text scores as an empty one; labelled ids without a document, documents without a label and null labels are
not learned from; repeated labels count as often as they stand; labels of one class only, or none, give the constant model of that
class (0.5 without any); an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Labelled rows that the model is fitted on at most; of each of their texts, all bytes.
FIT_ROWS = 4000
#: log2 of the number of hashed features.
WIDTH = 16
THRESHOLD = 0.3
FOLDS = 5
#: Strength of the loss, rounds over the rows at most.
COST, ROUNDS = 1.0, 12



def _grams(text: str) -> np.ndarray:
    """Hashed n-grams of one text, repeats included; every text has at least one."""
    raw = np.frombuffer(b" " + text.encode("utf-8", "surrogatepass") + b" ", np.uint8)
    low = np.where((raw >= 65) & (raw <= 90), 97, np.where((raw >= 97) & (raw <= 122), 97, np.where((raw >= 48) & (raw <= 57), 48, np.where(raw >= 128, 200, raw)))).astype(np.uint32)
    case = np.where((raw >= 65) & (raw <= 90), 65, low).astype(np.uint32)
    words = raw.astype(np.uint32) | np.uint32(32) * ((raw >= 65) & (raw <= 90))
    out = []
    for salt, codes, sizes in ((1, case, (2, 3, 5)), (2, words, (3,))):
        for n in sizes:
            if len(codes) < n:
                continue
            h = np.full(len(codes) - n + 1, salt * 64 + n, np.uint32)
            for k in range(n):
                h = h * np.uint32(0x9E3779B1) + codes[k : len(codes) - n + 1 + k]
            h ^= h >> np.uint32(15)
            h *= np.uint32(0x85EBCA6B)
            out.append(h >> np.uint32(32 - WIDTH))
    return np.concatenate(out)


def features(text: str, seen: np.ndarray | None = None) -> np.ndarray:
    """Indices of the features that the text has, each once. seen: a scratch array of the features' number."""
    idx = _grams(text)
    if seen is None:
        return np.unique(idx)
    place = np.arange(len(idx), dtype=np.int32)
    seen[idx] = place
    return idx[seen[idx] == place]


def log_count_ratio(rows: list[np.ndarray], labels: np.ndarray, smooth: float = 1.0) -> np.ndarray:
    """Per feature: log of its share among class 1's indicators over that among class 0's."""
    sums = []
    for c in (1, 0):
        own = [r for r, y in zip(rows, labels, strict=True) if y == c]
        p = smooth + (np.bincount(np.concatenate(own), minlength=1 << WIDTH) if own else np.zeros(1 << WIDTH))
        sums.append(p / p.sum())
    return np.log(sums[0] / sums[1])


def dual_descent(rows: list[np.ndarray], values: list[np.ndarray], labels: np.ndarray, cost: np.ndarray, rounds: int = ROUNDS, seed: int = 1) -> tuple[np.ndarray, float]:
    """Weights and bias of the squared hinge loss; one dual variable per row, each solved exactly in turn. cost: per row."""
    w, bias = np.zeros(1 << WIDTH), 0.0
    y = np.where(labels == 1, 1.0, -1.0)
    alpha, ridge = np.zeros(len(rows)), 0.5 / cost
    square = np.array([v @ v + 1.0 for v in values]) + ridge
    order = np.random.default_rng(seed)
    for _ in range(rounds):
        most = 0.0
        for i in order.permutation(len(rows)):
            g = y[i] * (w[rows[i]] @ values[i] + bias) - 1.0 + ridge[i] * alpha[i]
            step = max(alpha[i] - g / square[i], 0.0) - alpha[i]
            if step:
                alpha[i] += step
                w[rows[i]] += step * y[i] * values[i]
                bias += step * y[i]
                most = max(most, abs(step))
        if most < 1e-4:
            break
    return w, bias


def _margins(rows, w, bias):
    return np.array([w[r].sum() / np.sqrt(len(r)) + bias for r in rows])


def fit_rows(texts: list[str], labels: np.ndarray, threshold: float = THRESHOLD) -> dict:
    """The model: w (already scaled by the ratios), bias, slope and shift of the logistic curve."""
    labels = np.asarray(labels)
    if len(set(labels.tolist())) < 2:
        constant = float(labels[0]) if len(labels) else 0.5
        return {"w": np.zeros(1 << WIDTH, np.float32), "bias": 0.0, "slope": 0.0, "shift": {1.0: 6.0, 0.0: -6.0}.get(constant, 0.0)}
    rows = [features(t) for t in texts]

    def train(keep):
        own, y = [rows[i] for i in keep], labels[keep]
        ratio = log_count_ratio(own, y)
        # indicators scaled by their ratio, each row to unit scale by its number of features
        values = [ratio[r] / np.sqrt(len(r)) for r in own]
        share = np.array([(y == c).mean() for c in (0, 1)])
        w, bias = dual_descent(own, values, y, COST * 0.5 / share[y])
        return (w * ratio).astype(np.float64), bias

    # margins of rows that the fit hasn't seen: two halves, each scored by the other's model
    half = np.arange(len(rows)) % 2
    margin = np.zeros(len(rows))
    for k in (0, 1):
        keep = np.flatnonzero(half != k)
        if len(set(labels[keep].tolist())) == 2:
            w, b = train(keep)
            margin[half == k] = _margins([rows[i] for i in np.flatnonzero(half == k)], w, b)
    w, bias = train(np.arange(len(rows)))
    cuts = np.unique(margin)
    pos, neg = np.sort(margin[labels == 1]), np.sort(margin[labels == 0])
    lost = np.searchsorted(pos, cuts, "left") / len(pos) * 2 + (len(neg) - np.searchsorted(neg, cuts, "left")) / len(neg)
    # of the equally good cuts, the middle one; a good row that is lost weighs twice a bad one that is kept
    best = np.flatnonzero(lost <= lost.min() + 1e-12)
    at = best[0]
    cut = (cuts[at] + (cuts[at - 1] if at else cuts[at] - 1)) / 2
    spread = max(np.median(np.abs(margin - cut)), 1e-6)
    slope = 2.0 / spread
    return {"w": w.astype(np.float32), "bias": float(bias), "slope": float(slope), "shift": float(np.log(threshold / (1 - threshold)) - slope * cut)}


def score(text: str, model: dict, seen: np.ndarray | None = None) -> float:
    idx = features(text, seen)
    margin = float(model["w"][idx].sum(dtype=np.float64)) / np.sqrt(len(idx)) + model["bias"] if len(idx) else model["bias"]
    return float(1.0 / (1.0 + np.exp(-np.clip(model["slope"] * margin + model["shift"], -40, 40))))


def held_out(id_col: str = "doc_id"):
    """Column: true for the rows that are never learned from."""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit(""))), F.lit(FOLDS)) == 0


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", most: int = FIT_ROWS, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> dict:
    """The model of label_col. One task fits it on at most so many rows; the driver gets the weights alone."""
    told = labels.where(F.col(label_col).isin(0, 1) & ~held_out(id_col)).select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("y"))
    chosen = told.orderBy(F.xxhash64("id"), "id", "y").limit(most)
    wanted = chosen.groupBy("id").agg(F.min("y").alias("y"))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), common.whole_text(docs, text_col).alias("text")).join(F.broadcast(wanted), "id")
    # fixed order: the rows' places among the hashes; one row per id
    one = rows.groupBy("id").agg(F.min("y").alias("y"), F.min("text").alias("text"))

    def learn(batches):
        pdf = pd.concat(list(batches), ignore_index=True)
        pdf = pdf.sort_values("id", key=lambda s: s.map(lambda i: zlib.crc32(str(i).encode()))).reset_index(drop=True)
        model = fit_rows(pdf["text"].tolist(), pdf["y"].to_numpy(), threshold)
        yield pd.DataFrame({"w": [model["w"].tobytes()], "bias": [model["bias"]], "slope": [model["slope"]], "shift": [model["shift"]]})

    got = one.coalesce(1).mapInPandas(learn, "w binary, bias double, slope double, shift double").collect()
    if not got:
        return fit_rows([], np.array([], int), threshold)
    return {"w": np.frombuffer(got[0]["w"], np.float32), "bias": got[0]["bias"], "slope": got[0]["slope"], "shift": got[0]["shift"]}


def with_score(docs: DataFrame, model: dict, text_col: str = "text", out: str = "score") -> DataFrame:
    """docs' columns with the score; a column of that name is replaced."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def scores(texts: pd.Series) -> pd.Series:
        seen = np.zeros(1 << WIDTH, np.int32)
        return pd.Series([score(t, sent.value, seen) for t in texts.fillna("")], dtype="float64")

    return docs.withColumn(out, scores(F.col(text_col)))


def labels_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def op9_nb_svm_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    model = fit(docs, labels_of(spark, sf_dir))
    scored = with_score(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


