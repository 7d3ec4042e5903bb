"""Contrastive objectives over representation vectors, and joint training."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import bucket

TAU, LAMBDA, DROP, BATCH = 0.05, 1.0, 0.1, 32  # our defaults; the values are not published


def dropout(vector: Column, key: Column, p: float = DROP, seed: str = "drop") -> Column:
    """A perturbed copy: coordinate i stays iff its hash bucket is at least p, scaled by 1/(1-p)."""
    return F.transform(vector, lambda x, i: F.when(bucket(F.concat_ws(":", key.cast("string"), i.cast("string")), seed) >= round(p * 10_000), x.cast("double") / (1 - p)).otherwise(F.lit(0.0)))


def _dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def _with_unit(df: DataFrame, vector: Column, name: str) -> DataFrame:
    """df with the unit vector; raw vector and norm are columns first, or each coordinate would compute them again."""
    normed = df.withColumn("_raw", vector).withColumn("_norm", F.sqrt(_dot(F.col("_raw"), F.col("_raw"))))
    unit = F.when(F.col("_norm") > 0, F.transform("_raw", lambda x: x / F.col("_norm"))).otherwise(F.col("_raw"))
    return normed.withColumn(name, unit).drop("_raw", "_norm")


def contrastive_loss(vectors: DataFrame, mode: str = "any", tau: float = TAU, p: float = DROP, seed: str = "drop") -> DataFrame:
    """batch_id, n, loss: each sample against its dropout copy and the copies of the others in its batch.

    mode "any": every other sample is pushed away; "class_aware": only those with another label. No negatives give
    loss 0. vectors: vec_id, batch_id, embedding, label."""
    base = vectors.select("batch_id", "vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    copies = _with_unit(base, dropout(F.col("v"), F.col("vec_id"), p, seed), "w").select("batch_id", F.col("vec_id").alias("other"), F.col("label").alias("other_label"), "w")
    anchors = _with_unit(base, F.col("v"), "u").select("batch_id", "vec_id", "label", "u")
    # a batch has a fixed number of members, so this join grows with the rows
    met = anchors.join(copies, "batch_id").select("batch_id", "vec_id", "other", "label", "other_label", (_dot(F.col("u"), F.col("w")) / tau).alias("s"))
    own = F.col("vec_id") == F.col("other")
    taken = met if mode == "any" else met.where(own | (F.col("label") != F.col("other_label")))
    per = taken.groupBy("batch_id", "vec_id").agg(F.max("s").alias("top"), F.collect_list("s").alias("all"), F.max(F.when(own, F.col("s"))).alias("positive"))
    spread = F.aggregate(F.sort_array("all"), F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top")))
    each = per.select("batch_id", (F.col("top") + F.ln(spread) - F.col("positive")).alias("l"))
    return each.groupBy("batch_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("l"), 6).alias("loss"))


def batch_pairs(vectors: DataFrame) -> DataFrame:
    """n ordered pairs inside batches, and how many carry different labels."""
    a, b = vectors.select("batch_id", "vec_id", "label"), vectors.select("batch_id", F.col("vec_id").alias("o"), F.col("label").alias("ol"))
    met = a.join(b, "batch_id").where("vec_id <> o")
    return met.agg(F.count(F.lit(1)).alias("n_pairs"), F.count_if(F.col("label") != F.col("ol")).alias("n_different"))


# --- joint training ---------------------------------------------------------------------------------------------------


def _contrast_step(x: np.ndarray, labels: np.ndarray, w: np.ndarray, mode: str, tau: float, p: float, rng) -> tuple[float, np.ndarray]:
    copy = x * (rng.random(x.shape) >= p) / (1 - p)
    u, v = x @ w, copy @ w
    lu, lv = np.linalg.norm(u, axis=1, keepdims=True) + 1e-12, np.linalg.norm(v, axis=1, keepdims=True) + 1e-12
    nu, nv = u / lu, v / lv
    s = nu @ nv.T / tau
    seen = np.ones_like(s, bool) if mode == "any" else labels[:, None] != labels[None, :]
    np.fill_diagonal(seen, True)
    s = np.where(seen, s, -np.inf)
    e = np.exp(s - s.max(1, keepdims=True))
    share = e / e.sum(1, keepdims=True)
    loss = -np.log(np.maximum(np.diag(share), 1e-300)).sum()
    g = (share - np.eye(len(x))) / tau
    gu, gv = g @ nv, g.T @ nu
    back = lambda grad, n, length: (grad - (grad * n).sum(1, keepdims=True) * n) / length
    return float(loss), x.T @ back(gu, nu, lu) + copy.T @ back(gv, nv, lv)


def fit_joint(train: DataFrame, mode: str = "none", lam: float = LAMBDA, epochs: int = 3, rate: float = 0.5, width: int = 16, tau: float = TAU, p: float = DROP, weight: float = 1.0, seed: int = 11) -> dict:
    """Linear projection and classifier under classification + lam * contrast (mode "none": classification only).

    train: batch_id, embedding, label (0/1). Each epoch sends the parameters out, sums the gradients of the batches in
    parallel and steps once; losses per epoch are returned with the parameters. lam = 0 equals mode "none"."""
    dim = len(train.select("embedding").first()[0])
    rng = np.random.default_rng(seed)
    w, a, c = rng.normal(0, dim**-0.5, (dim, width)), np.zeros(width), 0.0
    a[:] = rng.normal(0, 0.1, width)
    history = []
    use = mode != "none" and lam > 0
    def gradients_at(state: tuple, epoch: int):
        def gradients(key, frame: pd.DataFrame) -> pd.DataFrame:
            w, a, c = state
            frame = frame.sort_values("vec_id")
            x, y = np.stack(frame["embedding"].to_list()).astype(float), frame["label"].to_numpy(float)
            u = x @ w
            q = 1 / (1 + np.exp(-(u @ a + c)))
            factor = np.where(y == 1, weight, 1.0)
            error = factor * (q - y)
            loss = -(factor * (y * np.log(q + 1e-12) + (1 - y) * np.log(1 - q + 1e-12))).sum()
            gw, ga, gc = x.T @ (error[:, None] * a), u.T @ error, error.sum()
            extra = 0.0
            if use:
                extra, more = _contrast_step(x, y, w, mode, tau, p, np.random.default_rng([seed, epoch, int(key[0])]))
                gw += lam * more
            return pd.DataFrame({"gradient": [np.r_[gw.ravel(), ga, gc, len(x), loss, extra].tolist()]})

        return gradients

    for epoch in range(epochs):
        parts = train.select("batch_id", "vec_id", "embedding", "label").groupBy("batch_id").applyInPandas(gradients_at((w, a, c), epoch), "gradient array<double>")
        # element-wise sums on the cluster: the driver gets one vector an epoch, with counts and losses behind it
        summed = parts.select(F.posexplode("gradient").alias("i", "g")).groupBy("i").agg(F.sum("g").alias("g"))
        total = np.zeros(dim * width + width + 4)
        for r in summed.collect():
            total[r["i"]] = r["g"]
        n, loss, extra = total[-3:]
        g = total[:-3] / n
        w, a, c = w - rate * g[: dim * width].reshape(dim, width), a - rate * g[dim * width : -1], c - rate * g[-1]
        history.append((epoch, float(loss / n), float(extra / n)))
    return {"w": w, "a": a, "c": float(c), "history": history}


def predict_joint(model: dict, df: DataFrame, threshold: float = 0.5) -> DataFrame:
    """sample_id, label, score, pred; the parameters are folded into one weight a coordinate."""
    direction = F.array(*[F.lit(float(x)) for x in model["w"] @ model["a"]])
    z = _dot(F.transform("embedding", lambda x: x.cast("double")), direction) + F.lit(model["c"])
    scored = df.withColumn("score", 1 / (1 + F.exp(-z)))
    return scored.withColumn("pred", (F.col("score") >= threshold).cast("int")).drop("embedding")


def describe(model: dict) -> str:
    return json.dumps([[e, round(a, 6), round(b, 6)] for e, a, b in model["history"]])
