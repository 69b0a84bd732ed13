"""Quality by positive-unlabelled learning: non-negative unbiased risk on text features.

Trusted positives are labelled rows of quality 1; everything else is an unlabelled draw of the
corpus. The class prior is estimated from the two samples (the least ratio of the unlabelled to
the positive tail over the score range, with a confidence margin). A small network minimises
``prior * R_pos(+) + max(0, R_unl(-) - prior * R_pos(-))`` by mini-batches; where the second term
turns negative the step goes the other way, so the risk cannot be driven below zero.

Fitting takes at most ``max_rows`` positives and as many unlabelled rows, both chosen by a hash of
the id; every row is scored on its whole text. Labels of 0 are not used as negatives.

Defined cases: a null or empty text has features 0 and is scored like any other; a null doc_id is
scored and is not held out; repeated rows are scored each; repeated labels count once (the
larger); without trusted positives every score is 0.5.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadlab.llm.common import RowBuffer, arrow_rows, table, tidy
from spreadlab.llm.toxicity import held_out, labelled_sample

CLASSES = np.zeros((256, 8), np.float32)  # columns: letter, upper, digit, space, stop or comma, table bar, other mark, non-ASCII
for _b in range(256):
    _c = chr(_b)
    CLASSES[_b, 7 if _b > 127 else 0 if _c.isalpha() else 2 if _c.isdigit() else 3 if _c.isspace() else 4 if _c in ".," else 5 if _c == "|" else 6] = 1
    CLASSES[_b, 1] = float("A" <= _c <= "Z")
N_FEATURES = 24


def features(text: str | None) -> np.ndarray:
    """Fixed-length description of a text: composition, repetition, word and line shapes."""
    out = np.zeros(N_FEATURES, np.float32)
    if not text:
        return out
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    if not words:
        return out
    counts = np.bincount(np.frombuffer(raw, np.uint8), minlength=256).astype(np.float32)
    out[0:8] = np.sqrt(counts @ CLASSES / len(raw))
    n = len(words)
    distinct = Counter(words)
    lengths = np.fromiter(map(len, words), np.float32, n)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    repeated = sum(a == b for a, b in zip(words, words[1:], strict=False))
    out[8] = math.log1p(n)
    out[9] = len(distinct) / n
    out[10] = math.log(len(distinct)) / math.log(n) if n > 1 else 1.0
    out[11] = max(distinct.values()) / n
    out[12] = repeated / n
    out[13] = lengths.mean() / 10
    out[14] = lengths.std() / 10
    out[15] = math.log1p(float(lengths.max()))
    out[16] = 1 - len(set(lines)) / len(lines)
    out[17] = math.log1p(n / len(lines))
    last = Counter(w[-1] for w in words)
    out[18] = sum(c for b, c in last.items() if not (b > 127 or chr(b).isalnum() or chr(b) in ".,")) / n
    out[19] = len(set(zip(words, words[1:], strict=False))) / max(1, n - 1)
    out[20] = sum(w.isupper() for w in words) / n
    out[21] = sum(w[:1].isdigit() for w in words) / n
    out[22] = float(np.mean(lengths <= 3))
    ends = sum(w[-1:] in (b".", b"!", b"?") for w in words)
    out[23] = ends / n
    return out


@dataclass
class PUModel:
    """Standardisation and weights of a one-hidden-layer scorer."""

    mean: np.ndarray
    scale: np.ndarray
    layers: list[np.ndarray]
    shift: float = 0.0

    def raw(self, x: np.ndarray) -> np.ndarray:
        w1, b1, w2, b2 = self.layers
        return np.tanh(np.clip((x - self.mean) / self.scale, -6, 6) @ w1 + b1) @ w2[:, 0] + b2[0] + self.shift

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -35, 35)))


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, delta: float = 0.1) -> float:
    """Class prior from held-aside scores: the least tail ratio, each with a deviation margin.

    If a score's upper tail holds positives only, the share of the unlabelled there over the share of
    the positives there is the prior; elsewhere the ratio is larger.
    """
    cuts = np.unique(np.concatenate([positive, unlabelled]))
    p = 1 - np.searchsorted(np.sort(positive), cuts, "left") / len(positive)
    u = 1 - np.searchsorted(np.sort(unlabelled), cuts, "left") / len(unlabelled)
    margin = math.sqrt(math.log(4 / delta) / 2) * (1 / math.sqrt(len(positive)) + 1 / math.sqrt(len(unlabelled)))
    usable = p > margin * 2
    if not usable.any():
        return 0.5
    at = np.argmin((u[usable] + margin) / p[usable])
    return float(np.clip(u[usable][at] / p[usable][at], 0.02, 0.98))


def train(positive: np.ndarray, unlabelled: np.ndarray, prior: float, seed: int = 5, hidden: int = 24, epochs: int = 60, rate: float = 0.01, non_negative: bool = True) -> PUModel:
    """Minimise the (non-negative) unbiased risk with the sigmoid loss by Adam."""
    rng = np.random.default_rng(seed)
    both = np.vstack([positive, unlabelled])
    mean, scale = both.mean(0), both.std(0) + 1e-3
    xp, xu = (np.clip((x - mean) / scale, -6, 6) for x in (positive, unlabelled))
    d = both.shape[1]
    layers = [rng.normal(0, 1 / math.sqrt(d), (d, hidden)), np.zeros(hidden), rng.normal(0, 1 / math.sqrt(hidden), (hidden, 1)), np.zeros(1)]
    m, v = [np.zeros_like(w) for w in layers], [np.zeros_like(w) for w in layers]
    batches, step = max(1, min(200, len(xu) // 256)), 0

    def forward(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = np.tanh(x @ layers[0] + layers[1])
        return h, (h @ layers[2])[:, 0] + layers[3][0]

    def backward(x: np.ndarray, h: np.ndarray, dz: np.ndarray) -> list[np.ndarray]:
        dh = dz[:, None] @ layers[2].T * (1 - h * h)
        return [x.T @ dh, dh.sum(0), h.T @ dz[:, None], np.array([dz.sum()])]

    for epoch in range(epochs):
        pp, uu = np.array_split(rng.permutation(len(xp)), min(batches, len(xp))), np.array_split(rng.permutation(len(xu)), batches)
        for b in range(batches):
            p, u = xp[pp[b % len(pp)]], xu[uu[b]]
            (hp, zp), (hu, zu) = forward(p), forward(u)
            sp, su = 1 / (1 + np.exp(-np.clip(zp, -30, 30))), 1 / (1 + np.exp(-np.clip(zu, -30, 30)))
            # sigmoid loss: l(z, +1) = s(-z), l(z, -1) = s(z)
            negative = su.mean() - prior * sp.mean()
            grow_p, grow_u = sp * (1 - sp) / len(p), su * (1 - su) / len(u)
            if non_negative and negative < 0:
                gp, gu = prior * grow_p, -grow_u
            else:
                gp, gu = -2 * prior * grow_p, grow_u
            grads = [a + c for a, c in zip(backward(p, hp, gp), backward(u, hu, gu), strict=True)]
            step += 1
            lr = rate * (0.5 + 0.5 * math.cos(math.pi * epoch / epochs))
            for i, g in enumerate(grads):
                g = g + 1e-4 * layers[i]
                m[i] = 0.9 * m[i] + 0.1 * g
                v[i] = 0.999 * v[i] + 0.001 * g * g
                layers[i] -= lr * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
    return PUModel(mean, scale, layers)


def fit_pu(positive: np.ndarray, unlabelled: np.ndarray) -> tuple[PUModel, float]:
    """Prior and model: a first model on half the rows scores the other half, from which the prior comes."""
    first = train(positive[::2], unlabelled[::2], 0.5, epochs=30)
    prior = estimate_prior(first.raw(positive[1::2]), first.raw(unlabelled[1::2])) if min(len(positive), len(unlabelled)) > 3 else 0.5
    return train(positive, unlabelled, prior), prior


def feature_rows(rows: DataFrame) -> DataFrame:
    """(x) of the texts in ``rows``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = [features(t) for (t,) in arrow_rows([b], "text")]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float32()))], ["x"])

    return rows.select("text").mapInArrow(tidy(run), "x array<float>")


def fit_quality(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", usable=None) -> tuple[PUModel | None, float]:
    """Fit on trusted positives among the usable labelled rows and an unlabelled draw of all documents."""
    usable = F.lit(True) if usable is None else usable
    trusted = labelled_sample(docs, labels.filter(F.col(label_col) == 1), usable, label_col, max_rows, id_col, text_col)
    plain = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).filter("id IS NOT NULL")
    n = plain.select("id").count()
    if n > max_rows:
        plain = plain.filter(F.pmod(F.xxhash64("id", F.lit(37)), F.lit(1 << 30)) / float(1 << 30) < max_rows / n)
    xp, xu = (np.array([r.x for r in feature_rows(d).collect()], np.float64) for d in (trusted, plain))
    if not len(xp) or not len(xu):
        return None, 0.5
    order = np.lexsort(xp.T), np.lexsort(xu.T)
    rng = np.random.default_rng(11)
    return fit_pu(rng.permutation(xp[order[0]]), rng.permutation(xu[order[1]]))


def score_quality(docs: DataFrame, model: PUModel | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, quality) of every row."""
    id_type = docs.schema[id_col].dataType
    schema = pa.schema([("id", pa.int64()), ("quality", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = np.stack([features(t) for (t,) in arrow_rows([b], "text")]).astype(np.float64)
            s = model.score(x) if model is not None else np.full(len(x), 0.5)
            yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("id")), pa.array(s, pa.float64())], schema=schema)

    scored = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), "id long, quality double")
    return scored.select(F.col("id").cast(id_type).alias("id"), "quality")


def op1_pu_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model, _ = fit_quality(docs, table(spark, sf_dir, "labels"), usable=~held_out(F.col("id"), 3, 1))
    scored = score_quality(docs, model)
    return scored.select(F.col("id").alias("doc_id"), held_out(F.col("id"), 3, 1).alias("held_out"), F.col("quality").alias("score"), (F.col("quality") >= 0.5).cast("int").alias("predicted"))


QUERIES = {"op1_pu_quality": op1_pu_quality}
