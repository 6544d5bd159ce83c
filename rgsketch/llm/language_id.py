"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Characters are lower-cased, all but letters become one blank, and runs of 1 to 4 characters are hashed into ``DIM`` columns.
Document frequencies are counted over all learning rows. The weights are fitted with follow-the-regularised-leader and
elastic-net penalties on a bounded sample (``per_class`` rows a class, the parameter documented here), a fifth of which is
kept back to choose the softmax temperature. Prediction reads each whole text.

Edge cases: a text that is null or has no letter gives ``und`` and score 0; with nothing to learn from, every row gives
``und`` and score 0; rows whose lang is null are predicted but not learned from; a null id counts as the empty string when
rows are held out; repeated rows are repeated results; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

UND = "und"
DIM = 1 << 13
ORDERS = (1, 2, 3, 4)
PER_CLASS = 600
#: Characters that one pass hashes; a longer text is counted piece by piece.
PIECE = 1 << 18
_NON_LETTER = re.compile(r"[\W\d_]+")
_MUL = [np.uint32(x) for x in (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F)]


def letters(text: str | None) -> str:
    """Lower-case letters with single blanks for all else; empty if there is no letter."""
    out = _NON_LETTER.sub(" ", (text or "").lower())
    return out if any(c.isalpha() for c in out) else ""


def counts(text: str) -> np.ndarray:
    """Hashed n-gram counts of ``letters(text)``, DIM of them."""
    out = np.zeros(DIM, np.int64)
    text = f" {text.strip()} "
    reach = max(ORDERS) - 1
    for at in range(0, len(text), PIECE):
        piece = text[at : at + PIECE + reach]
        codes = np.frombuffer(piece.encode("utf-32-le", "surrogatepass"), np.uint32)
        own, h = min(PIECE, len(text) - at), np.zeros(len(codes), np.uint32)
        for k in ORDERS:
            n = len(codes) - k + 1
            if n <= 0:
                break
            h = (h[:n] ^ codes[k - 1 : k - 1 + n]) * _MUL[k - 1]
            h ^= h >> np.uint32(15)
            out += np.bincount((h[: min(own, n)] >> np.uint32(19)).astype(np.int64), minlength=DIM)
    return out


assert 32 - 19 == DIM.bit_length() - 1


@dataclass
class Model:
    classes: list[str]
    idf: np.ndarray
    weights: np.ndarray  # DIM x classes
    bias: np.ndarray
    temperature: float = 1.0

    def features(self, text: str) -> np.ndarray:
        x = np.sqrt(counts(text)) * self.idf
        return x / max(np.linalg.norm(x), 1e-12)

    def logits(self, x: np.ndarray) -> np.ndarray:
        return x @ self.weights + self.bias

    def predict(self, text: str | None) -> tuple[str, float]:
        clean = letters(text)
        if not clean or not self.classes:
            return UND, 0.0
        p = softmax(self.logits(self.features(clean)) / self.temperature)
        best = int(p.argmax())
        return self.classes[best], float(p[best])


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def fit_ftrl(x: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, n_classes: int, epochs: int = 4, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.1, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Weights and bias after passes over sparse rows (columns, values), one row at a time in a seeded order."""
    z, n = np.zeros((DIM + 1, n_classes)), np.zeros((DIM + 1, n_classes))
    rng = np.random.default_rng(seed)

    def current(cols):
        zc = z[cols]
        return np.where(np.abs(zc) <= l1, 0.0, -(zc - np.sign(zc) * l1) / ((beta + np.sqrt(n[cols])) / alpha + l2))

    for _ in range(epochs):
        for i in rng.permutation(len(x)):
            cols, vals = np.append(x[i][0], DIM), np.append(x[i][1], 1.0)
            w = current(cols)
            g = softmax(vals @ w)
            g[y[i]] -= 1.0
            g = vals[:, None] * g
            z[cols] += g - (np.sqrt(n[cols] + g * g) - np.sqrt(n[cols])) / alpha * w
            n[cols] += g * g
    w = current(np.arange(DIM + 1))
    return w[:DIM], w[DIM]


def calibrate(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature of least log loss, by a fixed geometric search."""
    if not len(y):
        return 1.0
    grid = np.geomspace(0.05, 5.0, 60)
    loss = [-np.log(np.maximum(softmax(logits / t)[np.arange(len(y)), y], 1e-12)).mean() for t in grid]
    return float(grid[int(np.argmin(loss))])


def _frequencies(batches):
    """One task's document frequencies: (column, rows that hold it), with the number of rows under column -1."""
    seen, total = np.zeros(DIM, np.int64), 0
    for batch in batches:
        for value in batch.column(0):
            clean = letters(value.as_py())
            if clean:
                seen += counts(clean) > 0
                total += 1
    at = np.flatnonzero(seen)
    yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1), pa.int32()), pa.array(np.append(seen[at], total), pa.int64())], ["col", "rows"])


def train(learn: DataFrame, per_class: int = PER_CLASS, max_classes: int = 1000, seed: int = 5) -> Model:
    """Fit on rows (text, lang, key); key is any string that orders the sample."""
    learn = learn.where("lang IS NOT NULL AND text IS NOT NULL")
    freq = {r["col"]: r["n"] for r in learn.select("text").mapInArrow(_frequencies, "col int, rows long").groupBy("col").agg(F.sum("rows").alias("n")).collect()}  # DIM + 1 rows at most
    sizes = {r["lang"]: r["count"] for r in learn.groupBy("lang").count().limit(max_classes + 1).collect()}
    if len(sizes) > max_classes:
        raise ValueError(f"more than {max_classes} classes")
    classes = sorted(sizes)
    total = freq.pop(-1, 0)
    df = np.zeros(DIM)
    for c, n in freq.items():
        df[c] = n
    idf = np.log((1 + total) / (1 + df)) + 1
    model = Model(classes, idf, np.zeros((DIM, len(classes))), np.zeros(len(classes)))
    if not classes:
        return model
    share = F.coalesce(*[F.when(F.col("lang") == c, F.lit(min(1.0, 2.0 * per_class / n))) for c, n in sizes.items()])
    draw = F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(1 << 40))
    near = learn.select("text", "lang", draw.alias("draw"), F.col("key")).where(F.col("draw") < share * float(1 << 40))
    first = near.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy("draw", "key", F.length("text"), "text"))).where(F.col("k") <= per_class)

    def rows(batches):
        for batch in batches:
            out = []
            for value in batch.column(0):
                c = counts(letters(value.as_py()))
                at = np.flatnonzero(c)
                out.append((at.astype(np.int16).tobytes(), np.minimum(c[at], 65535).astype(np.uint16).tobytes()))
            a, b = zip(*out, strict=True) if out else ([], [])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary()), batch.column(1), batch.column(2)], ["cols", "vals", "lang", "k"])

    got = first.select("text", "lang", "k").mapInArrow(rows, "cols binary, vals binary, lang string, k int").collect()  # per_class rows a class at most
    got.sort(key=lambda r: (r["k"], r["lang"]))
    x, y, kept = [], [], []
    for r in got:
        at = np.frombuffer(r["cols"], np.int16).astype(np.int64)
        if len(at):
            v = np.sqrt(np.frombuffer(r["vals"], np.uint16)) * idf[at]
            x.append((at, v / np.linalg.norm(v)))
            y.append(classes.index(r["lang"]))
            kept.append(r["k"] % 5 == 0)
    y, kept = np.array(y, np.int64), np.array(kept, bool)
    model.weights, model.bias = fit_ftrl([x[i] for i in np.flatnonzero(~kept)], y[~kept], len(classes), seed=seed)
    held = np.array([v @ model.weights[c] + model.bias for c, v in (x[i] for i in np.flatnonzero(kept))]).reshape(-1, len(classes))
    model.temperature = calibrate(held, y[kept])
    return model


def predict(df: DataFrame, model: Model) -> DataFrame:
    """df with lang_pred and score in the place of column ``text``, which comes first; the others are carried."""
    rest = [f for f in df.schema.fields if f.name != "text"]
    df = df.select(df["text"].cast("string"), *[df[f.name] for f in rest])
    kind = T.StructType([*(df.schema[f.name] for f in rest), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def run(batches):
        for batch in batches:
            lang, score = zip(*[model.predict(t.as_py()) for t in batch.column(0)], strict=True) if batch.num_rows else ([], [])
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(lang, pa.string()), pa.array(score, pa.float64())], [*batch.schema.names[1:], "lang_pred", "score"])

    return df.mapInArrow(run, kind)


def held_out(id_col: F.Column) -> F.Column:
    return F.pmod(F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def learn_from(docs: DataFrame, per_class: int = PER_CLASS) -> Model:
    """The model of the documents whose id isn't held out."""
    key = F.coalesce(docs["doc_id"].cast("string"), F.lit(""))
    return train(docs.select("text", "lang", key.alias("key"), held_out(docs["doc_id"]).alias("h")).where("NOT h").drop("h"), per_class)


def identify(docs: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    rows = docs.select(docs["text"], docs["doc_id"], held_out(docs["doc_id"]).alias("held_out"))
    return predict(rows, learn_from(docs, per_class)).select("doc_id", "held_out", "lang_pred", "score")


def query(spark, sf_dir: str) -> DataFrame:
    return identify(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def keep_known(docs: DataFrame, least_score: float = 0.5) -> DataFrame:
    """Rows whose language is recognised with the given calibrated probability; ``und`` rows go. Columns stay as they are.

    The text goes to Python once, within the row.
    """
    model = learn_from(docs)
    packed = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("rec"))
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            found = [model.predict(t.as_py()) for t in batch.column(0).field(at)]
            yield batch.filter(pa.array([lang != UND and score >= least_score for lang, score in found], pa.bool_()))

    return packed.mapInArrow(run, packed.schema).select("rec.*")
