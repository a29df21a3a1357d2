"""The trainable part: a shared projection with a label head, and beside it the heads of the auxiliary task and of the baselines.

Every loss has a hand-written gradient, checked against finite differences in the tests. Inputs are dense blocks of hashed bags.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np


@dataclass(frozen=True)
class TrainConfig:
    """Settings of a run. ``paper_settings`` names the published values; the small models here need a larger rate.

    ``centred`` measures polarity from the source's label prior, and ``min_labelled`` asks for support: with labels as uneven as those of the
    given tables, the plain score ranks every rare word of the common label first and the banks have nothing to learn.
    ``labelled_rows`` and ``unlabelled_rows`` bound the texts of one step; a fit goes over all texts.
    """

    dims: int = 4096
    hidden: int = 24
    rate: float = 0.02
    warmup: float = 0.1
    steps: int = 150
    weight_decay: float = 1e-4
    head_every: int = 1
    gamma: float = 0.25
    lam: float = 0.3
    branch_gamma: float = 0.5
    balanced: bool = True
    epochs: int = 2
    k: int = 50
    theta: float = 0.9
    alpha: float = 0.95
    tau: float = 0.3
    centred: bool = True
    min_labelled: int = 3
    per_pivot: int = 2
    labelled_rows: int = 1600
    unlabelled_rows: int = 2000
    seed: int = 0


def paper_settings() -> TrainConfig:
    return replace(TrainConfig(), rate=2e-5, warmup=0.1, weight_decay=1e-4, k=500, theta=0.9, alpha=1 - 1e-4, head_every=5, centred=False, min_labelled=1)


@dataclass
class Batch:
    """Blocks of one run: labelled source, unlabelled source and target; ``m`` are the same texts with hidden pivots, ``k`` pivot shares of each text."""

    x: np.ndarray
    y: np.ndarray
    xs: np.ndarray
    xt: np.ndarray
    m: np.ndarray | None = None
    k: np.ndarray | None = None
    m_lab: np.ndarray | None = None
    signs: np.ndarray | None = None


@dataclass
class Net:
    p: dict[str, np.ndarray]
    hier: bool = False
    history: list[float] = field(default_factory=list)

    def logits(self, x: np.ndarray, masked: np.ndarray | None = None) -> np.ndarray:
        if self.hier:
            v = np.concatenate((_attend(x, self.p["E"], self.p["u"])[0], masked @ self.p["N"]), axis=1)
        else:
            v = x @ self.p["E"]
        return v @ self.p["W"] + self.p["b"]

    def p_pos(self, x: np.ndarray, masked: np.ndarray | None = None) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x, masked)[:, 0], -40, 40)))


def new_net(cfg: TrainConfig, k: int, hier: bool = False) -> Net:
    rng = np.random.default_rng(cfg.seed)
    h, d = cfg.hidden, cfg.dims
    p = {"E": rng.standard_normal((d, h)) * 0.1, "W": rng.standard_normal((2 * h if hier else h, 1)) * 0.1, "b": np.zeros(1)}
    if hier:
        p |= {"u": rng.standard_normal(h) * 0.1, "N": rng.standard_normal((d, h)) * 0.1, "S": np.zeros((h, 2))}
    p |= {"A": np.zeros((h, max(k, 1))), "D": rng.standard_normal((h, 1)) * 0.1, "d": np.zeros(1)}
    return Net(p, hier)


def _attend(x: np.ndarray, e: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Attention pooling: a word's share is its weight in the text times the exponential of its score."""
    z = x * np.exp(e @ u)[None, :]
    z = z / np.maximum(z.sum(axis=1, keepdims=True), 1e-12)
    return z @ e, z


def _logistic(z: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[float, np.ndarray]:
    """Mean weighted cross-entropy of 0/1 targets, and its gradient by the logits."""
    p = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    loss = -(w * (y * np.log(np.maximum(p, 1e-12)) + (1 - y) * np.log(np.maximum(1 - p, 1e-12)))).sum() / max(w.sum(), 1e-12)
    return float(loss), w * (p - y) / max(w.sum(), 1e-12)


def label_loss(net: Net, b: Batch, balanced: bool) -> tuple[float, dict[str, np.ndarray]]:
    """Cross-entropy on labelled source texts, classes weighed alike if ``balanced``."""
    p, y = net.p, (b.y > 0).astype(float)[:, None]
    n1, n0 = y.sum(), len(y) - y.sum()
    w = np.where(y > 0, len(y) / (2 * max(n1, 1)), len(y) / (2 * max(n0, 1))) if balanced else np.ones_like(y)
    if not net.hier:
        v = b.x @ p["E"]
        loss, dz = _logistic(v @ p["W"] + p["b"], y, w)
        return loss, {"W": v.T @ dz, "b": dz.sum(axis=0), "E": b.x.T @ (dz @ p["W"].T)}
    h = p["E"].shape[1]
    vp, z = _attend(b.x, p["E"], p["u"])
    vn = b.m_lab @ p["N"]
    v = np.concatenate((vp, vn), axis=1)
    loss, dz = _logistic(v @ p["W"] + p["b"], y, w)
    dv = dz @ p["W"].T
    g = dv[:, :h] @ p["E"].T
    ds = (z * (g - (z * g).sum(axis=1, keepdims=True))).sum(axis=0)
    return loss, {"W": v.T @ dz, "b": dz.sum(axis=0), "E": z.T @ dv[:, :h] + np.outer(ds, p["u"]), "u": p["E"].T @ ds, "N": b.m_lab.T @ dv[:, h:]}


def pivot_loss(net: Net, m: np.ndarray, k: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """Cross-entropy of recovering hidden pivots from the rest; ``k`` has each text's shares over the pivots."""
    v = m @ net.p["E"]
    z = v @ net.p["A"]
    z = z - z.max(axis=1, keepdims=True)
    logp = z - np.log(np.exp(z).sum(axis=1, keepdims=True))
    n = max(len(m), 1)
    dz = (np.exp(logp) * k.sum(axis=1, keepdims=True) - k) / n
    return float(-(k * logp).sum() / n), {"A": v.T @ dz, "E": m.T @ (dz @ net.p["A"].T)}


def sign_loss(net: Net, m: np.ndarray, signs: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """The hidden-pivot branch predicts whether pivots of either sign were there."""
    v = m @ net.p["N"]
    loss, dz = _logistic(v @ net.p["S"], signs, np.ones_like(signs))
    return loss, {"S": v.T @ dz, "N": m.T @ (dz @ net.p["S"].T)}


def domain_loss(net: Net, xs: np.ndarray, xt: np.ndarray, gamma: float) -> tuple[float, dict[str, np.ndarray]]:
    """Domain cross-entropy: the head descends, the shared projection gets the gradient reversed and scaled by ``gamma``."""
    x = np.concatenate((xs, xt))
    y = np.concatenate((np.zeros(len(xs)), np.ones(len(xt))))[:, None]
    v = x @ net.p["E"]
    loss, dz = _logistic(v @ net.p["D"] + net.p["d"], y, np.ones_like(y))
    return loss, {"D": v.T @ dz, "d": dz.sum(axis=0), "E": -gamma * (x.T @ (dz @ net.p["D"].T))}


def warm(step: int, steps: int, share: float) -> float:
    """Linear warm-up from 0 to 1 over a share of the steps."""
    return min(1.0, (step + 1) / max(1.0, share * steps))


def fit(net: Net, blocks: Batch | Callable[[int], Batch], cfg: TrainConfig, adversarial: bool = False, auxiliary: bool = False, steps: int | None = None) -> Net:
    """Adam over whole blocks, one for all steps or each step's own; the label head moves every ``head_every`` steps only."""
    steps = cfg.steps if steps is None else steps
    moments = {n: (np.zeros_like(v), np.zeros_like(v)) for n, v in net.p.items()}
    for step in range(steps):
        b = blocks(step) if callable(blocks) else blocks
        total, grads = label_loss(net, b, cfg.balanced) if len(b.y) else (0.0, {})
        if auxiliary and b.m is not None and len(b.m):
            scale = cfg.lam * warm(step, steps, 0.1)
            more, g = (sign_loss(net, b.m, b.signs) if net.hier else pivot_loss(net, b.m, b.k))
            total += scale * more
            for n, v in g.items():
                grads[n] = grads.get(n, 0) + scale * v
        if adversarial and len(b.xs) and len(b.xt):
            _, g = domain_loss(net, b.xs, b.xt, cfg.gamma)
            for n, v in g.items():
                grads[n] = grads.get(n, 0) + v
        net.history.append(total)
        rate = cfg.rate * warm(step, steps, cfg.warmup)
        for n, g in grads.items():
            if n in ("W", "b") and step % cfg.head_every:
                continue
            m1, m2 = moments[n]
            g = g + cfg.weight_decay * net.p[n]
            m1 += 0.1 * (g - m1)
            m2 += 0.001 * (g * g - m2)
            net.p[n] = net.p[n] - rate * (m1 / (1 - 0.9 ** (step + 1))) / (np.sqrt(m2 / (1 - 0.999 ** (step + 1))) + 1e-8)
    return net


def post_train(net: Net, block: Callable[[int], np.ndarray], n: int, cfg: TrainConfig, words: int = 200) -> Net:
    """Masked-word training on the target's ``n`` blocks: the commonest buckets are hidden in turn and recovered from the rest of the text."""
    seen = sum((block(i) > 0).sum(axis=0) for i in range(n))
    if not seen.any():
        return net
    top = np.argsort(-seen, kind="stable")[:words]

    def masked(i: int) -> tuple[np.ndarray, np.ndarray]:
        m, rng = block(i).copy(), np.random.default_rng(cfg.seed + i)
        hide = (m[:, top] > 0) & (rng.random((len(m), len(top))) < 0.3)
        m[:, top] = np.where(hide, 0, m[:, top])
        return m, hide / np.maximum(hide.sum(axis=1, keepdims=True), 1)

    keep, net.p["A"] = net.p["A"], np.zeros((net.p["E"].shape[1], len(top)))
    for step in range(max(cfg.steps // 3, n)):
        if step < 1 or n > 1:
            m, k = masked(step % n)
        _, g = pivot_loss(net, m, k)
        for name, v in g.items():
            net.p[name] = net.p[name] - 50 * cfg.rate * v
    net.p["A"] = keep
    return net
