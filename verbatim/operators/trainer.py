"""Gradient descent on the policy's weights.

The design (a row a sequence) is joined into rows of one item each (a pair, or a forget or
retain text) and cut off once; a step is one mapInPandas pass with theta broadcast, and only a
sum for each partition comes back, so nothing but theta grows on the driver.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.store import cut
from . import policy as P


def sequence_logp(positions, theta: np.ndarray, want_grad: bool, reference: np.ndarray | None = None) -> tuple[float, float, np.ndarray | None]:
    """(ln p under theta, ln p under the frozen reference, gradient) of one row of the design, token by token; without a reference, under theta = 0."""
    now = ref = 0.0
    grad = np.zeros(len(theta)) if want_grad else None
    for p in positions:
        base = np.asarray(p["logp"])
        feats = p["feats"]
        who = np.repeat(np.arange(len(base)), [len(f) for f in feats])
        what = np.concatenate([np.asarray(f) for f in feats]).astype(int)
        s = base + np.bincount(who, theta[what], len(base))
        s = s - s.max()
        e = np.exp(s)
        t = p["target"]
        now += s[t] - np.log(e.sum())
        b = base if reference is None else base + np.bincount(who, reference[what], len(base))
        b = b - b.max()
        ref += b[t] - np.log(np.exp(b).sum())
        if want_grad:
            d = -e / e.sum()
            d[t] += 1
            np.add.at(grad, what, d[who])
    return now, ref, grad


def items(design: DataFrame, roles: DataFrame) -> DataFrame:
    """(item_id, role, positions) from roles(item_id, role, seq_id): all roles of an item in one partition, one after the other."""
    d = design.join(roles, "seq_id")
    return cut(d.groupBy("item_id").agg(F.collect_list(F.struct("role", "positions")).alias("parts")))


def step(data: DataFrame, objective, theta: np.ndarray, reference: np.ndarray | None = None) -> tuple[float, np.ndarray, int]:
    """Mean loss, mean gradient and the number of items at theta."""
    blob = data.sparkSession.sparkContext.broadcast(pickle.dumps((objective, theta, reference)))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        objective, theta, reference = pickle.loads(blob.value)
        loss, grad, n = 0.0, np.zeros(len(theta)), 0
        for b in batches:
            for parts in b["parts"]:
                known = {x["role"]: sequence_logp(x["positions"], theta, True, reference) for x in parts}
                got, coefs = objective.terms({k: v[:2] for k, v in known.items()})
                loss, n = loss + got, n + 1
                for role, c in coefs.items():
                    grad += c * known[role][2]
        yield pd.DataFrame({"loss": [loss], "n": [n], "grad": [grad.tolist()]})

    rows = data.select("parts").mapInPandas(run, "loss double, n long, grad array<double>")
    got = rows.collect()
    blob.unpersist()
    n = sum(r["n"] for r in got)
    return sum(r["loss"] for r in got) / max(1, n), np.sum([r["grad"] for r in got], axis=0) / max(1, n), n


def fit(data: DataFrame, objective, start: P.Policy, rate: float = 1.0, steps: int = 8, tol: float = 1e-4, clip: float = 4.0, reference: np.ndarray | None = None) -> tuple[P.Policy, list[float]]:
    """Plain descent from `start`, which stays the frozen reference unless another is given; weights stay within +-clip of the start. Returns policy and losses."""
    theta, losses = start.theta.copy(), []
    reference = start.theta if reference is None else reference
    for _ in range(steps):
        loss, grad, _n = step(data, objective, theta, reference)
        losses.append(loss)
        if len(losses) > 1 and abs(losses[-2] - loss) < tol:
            break
        theta = np.clip(theta - rate * grad, start.theta - clip, start.theta + clip)
    return P.Policy(theta, start.lexical, {"objective": repr(objective), "rate": rate, "steps": len(losses), "clip": clip}), losses


def fit_lowrank(data: DataFrame, objective, rank: int = 4, rate: float = 1.0, steps: int = 8, seed: int = 1, start: P.Policy | None = None) -> tuple[P.Policy, list[float]]:
    """Only the lexical block is tuned, by a product of two thin factors that is added to the start's; the gradient reaches them by the chain rule."""
    start = P.widened(start or P.identity(True), True)
    rng = np.random.default_rng(seed)
    b = P.BUCKETS
    left, right = rng.normal(0, 0.1, (b, rank)), np.zeros((rank, b))
    losses = []
    at = len(start.theta) - b * b
    put = lambda: start.theta + np.r_[np.zeros(at), (left @ right).ravel()]
    for _ in range(steps):
        loss, grad, _n = step(data, objective, put(), start.theta)
        losses.append(loss)
        g = grad[at:].reshape(b, b)
        left, right = left - rate * g @ right.T, right - rate * left.T @ g
    return P.Policy(put(), True, {"rank": rank, "rate": rate}), losses


def score(design: DataFrame, theta: np.ndarray, reference: np.ndarray | None = None) -> DataFrame:
    """(seq_id, n_tokens, logp, logp_ref) of every row of the design."""
    blob = design.sparkSession.sparkContext.broadcast((theta, reference))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        theta, reference = blob.value
        for b in batches:
            got = [sequence_logp(p, theta, False, reference)[:2] for p in b["positions"]]
            yield pd.DataFrame({"seq_id": b["seq_id"], "n_tokens": [len(p) for p in b["positions"]], "logp": [g[0] for g in got], "logp_ref": [g[1] for g in got]})

    return design.mapInPandas(run, "seq_id string, n_tokens long, logp double, logp_ref double")


def scores(design: DataFrame, thetas: dict) -> DataFrame:
    """(policy, seq_id, logp) under many weights in one pass."""
    blob = design.sparkSession.sparkContext.broadcast(thetas)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for who, theta in blob.value.items():
                yield pd.DataFrame({"policy": who, "seq_id": b["seq_id"], "logp": [sequence_logp(p, theta, False)[0] for p in b["positions"]]})

    return design.mapInPandas(run, "policy string, seq_id string, logp double")
