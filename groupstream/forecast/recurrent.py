"""The interest forecaster: a recurrent autoencoder over profile sequences that predicts the next profile."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..encoder.training import Adam, sigmoid
from ..functions.linalg import add, matvec, zeros


def rnn_encode(rows: DataFrame, w_in, w_back, b, h: int) -> DataFrame:
    """(g, hidden): a plain tanh cell folded over each sequence, as one column expression for small cells."""

    def cell(state, item):
        new = add(matvec(w_in, item["profile"], b), matvec(w_back, state))
        return F.transform(new, F.tanh)

    return rows.select("g", F.aggregate("seq", zeros(h), cell).alias("hidden"))


def rnn_decode(rows: DataFrame, w_out, b) -> DataFrame:
    """(g, predicted): the profile of the next slice."""
    return rows.select("g", matvec(w_out, F.col("hidden"), b).alias("predicted"))


def new_weights(d: int, h: int, cell: str = "rnn", seed: int = 0, start: np.ndarray | None = None) -> dict[str, np.ndarray]:
    """Random weights; with `start`, predictions begin near that profile."""
    rng = np.random.default_rng(seed)
    gates = {"rnn": [""], "gru": ["", "z", "r"]}[cell]
    made = {f"w{k}": rng.normal(0, 0.3, (h, d)) for k in gates} | {f"u{k}": rng.normal(0, 0.3, (h, h)) for k in gates} | {f"b{k}": np.zeros(h) for k in gates}
    return made | {"wo": rng.normal(0, 0.3 if start is None else 0.05, (d, h)), "bo": np.zeros(d) if start is None else np.array(start, np.float64)}


def run_cell(w: dict, x: np.ndarray) -> tuple[np.ndarray, list]:
    """The last hidden state of sequences x (n, t, d), and what back-propagation needs."""
    h, kept = np.zeros((len(x), len(w["b"]))), []
    for t in range(x.shape[1]):
        if "wz" in w:
            z, r = (sigmoid(x[:, t] @ w[f"w{k}"].T + h @ w[f"u{k}"].T + w[f"b{k}"]) for k in "zr")
            c = np.tanh(x[:, t] @ w["w"].T + (r * h) @ w["u"].T + w["b"])
            kept.append((h, z, r, c))
            h = (1 - z) * h + z * c
        else:
            new = np.tanh(x[:, t] @ w["w"].T + h @ w["u"].T + w["b"])
            kept.append((h, new))
            h = new
    return h, kept


def loss_and_gradients(w: dict, x: np.ndarray, y: np.ndarray, penalty: float):
    """Squared error of the predicted next profile plus the penalty, and its gradient."""
    h, kept = run_cell(w, x)
    off = h @ w["wo"].T + w["bo"] - y
    loss = (off * off).sum() + penalty * sum((v * v).sum() for v in w.values())
    g = {k: 2 * penalty * v for k, v in w.items()}
    g["wo"], g["bo"] = g["wo"] + 2 * off.T @ h, g["bo"] + 2 * off.sum(0)
    dh = 2 * off @ w["wo"]
    for t in range(x.shape[1] - 1, -1, -1):
        if "wz" in w:
            h0, z, r, c = kept[t]
            dc, dz = dh * z * (1 - c * c), dh * (c - h0) * z * (1 - z)
            dr = (dc @ w["u"]) * h0 * r * (1 - r)
            for k, dk, hk in (("", dc, r * h0), ("z", dz, h0), ("r", dr, h0)):
                g[f"w{k}"], g[f"u{k}"], g[f"b{k}"] = g[f"w{k}"] + dk.T @ x[:, t], g[f"u{k}"] + dk.T @ hk, g[f"b{k}"] + dk.sum(0)
            dh = dh * (1 - z) + (dc @ w["u"]) * r + dz @ w["uz"] + dr @ w["ur"]
        else:
            h0, new = kept[t]
            da = dh * (1 - new * new)
            g["w"], g["u"], g["b"] = g["w"] + da.T @ x[:, t], g["u"] + da.T @ h0, g["b"] + da.sum(0)
            dh = da @ w["u"]
    return loss, g


def _matrix(seqs) -> np.ndarray:
    return np.array([[p["profile"] for p in s] for s in seqs], np.float64)


def train(rows: DataFrame, weights: dict, rate: float = 1e-2, penalty: float = 1e-5, epochs: int = 30, tolerance: float = 1e-4) -> tuple[dict, list[dict]]:
    """All slices but the last predict the last one. Sequences of one length are batched within a partition."""
    adam, log, began, weights = Adam(rate), [], time.time(), dict(weights)
    long = rows.where(F.size("seq") > 1).select("seq")
    for epoch in range(epochs):
        now = dict(weights)

        def run(batches, now=now):
            sums, n = {"loss": np.zeros(1)}, 0
            for b in batches:
                for _, part in b.groupby(b["seq"].map(len)):
                    x = _matrix(part["seq"])
                    loss, g = loss_and_gradients(now, x[:, :-1], x[:, -1], 0.0)
                    n += len(x)
                    sums["loss"] = sums["loss"] + loss
                    sums |= {k: sums.get(k, 0) + v for k, v in g.items()}
            yield pd.DataFrame([(k, np.ravel(v).tolist(), n) for k, v in sums.items()], columns=["name", "value", "n"])

        def total(part):
            return pd.DataFrame({"name": [part["name"].iloc[0]], "value": [np.sum(part["value"].tolist(), axis=0)], "n": [int(part["n"].sum())]})

        partial = long.mapInPandas(run, "name string, value array<double>, n long")
        sums = {r["name"]: (np.array(r["value"]), r["n"]) for r in partial.groupBy("name").applyInPandas(total, "name string, value array<double>, n long").collect()}  # a row per weight matrix
        if len(sums) < 2:
            break
        n = max(1, sums["loss"][1])
        log.append({"epoch": epoch, "loss": float(sums["loss"][0][0]) / n, "seconds": time.time() - began})
        adam.step(weights, {k: (sums[k][0] / n).reshape(v.shape) + 2 * penalty * v for k, v in weights.items()})
        if len(log) > 1 and abs(log[-2]["loss"] - log[-1]["loss"]) < tolerance * abs(log[-2]["loss"]):
            break
    return weights, log


def predict(rows: DataFrame, weights: dict) -> DataFrame:
    """(g, predicted): each group's profile in the slice after its last one."""

    def run(batches):
        for b in batches:
            for _, part in b.groupby(b["seq"].map(len)):
                h, _ = run_cell(weights, _matrix(part["seq"]))
                yield pd.DataFrame({"g": part["g"].to_numpy(), "predicted": list(h @ weights["wo"].T + weights["bo"])})

    return rows.where(F.size("seq") > 0).select("g", "seq").mapInPandas(run, "g long, predicted array<double>")
