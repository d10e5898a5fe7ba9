"""Domain-level mixers on n-gram proxies. Each yields (domain, weight) with weights of sum 1.

The domain x token table is aggregated in Spark; the optimisers then work on an array of domains x vocabulary, at most
``MAX_CELLS`` numbers, checked before it is taken to the driver.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .domains import normalise

MAX_CELLS = 4_000_000


@dataclass
class Table:
    """Smoothed token distributions of the domains, their token counts, and the vocabulary."""

    names: list[str]
    p: np.ndarray
    tokens: np.ndarray

    @property
    def natural(self) -> np.ndarray:
        return self.tokens / self.tokens.sum()


def table(counts: DataFrame, smooth: float = 0.5) -> Table:
    """From (domain, t, n)."""
    cells = counts.count()
    if cells > MAX_CELLS:
        raise ValueError(f"{cells} cells; hash the vocabulary into fewer buckets")
    pdf = counts.toPandas()
    wide = pdf.pivot_table(index="domain", columns="t", values="n", aggfunc="sum", fill_value=0).sort_index()
    n = wide.to_numpy(float)
    return Table([str(x) for x in wide.index], (n + smooth) / (n + smooth).sum(1, keepdims=True), n.sum(1))


def frame(spark: SparkSession, names: list[str], weights: np.ndarray) -> DataFrame:
    w = weights / weights.sum()
    return spark.createDataFrame([(n, float(x)) for n, x in zip(names, w, strict=True)], "domain string, weight double")


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max())
    return e / e.sum()


def cond_entropy(entropies: DataFrame, norm: str = "proportional") -> DataFrame:
    """From (domain, entropy)."""
    if norm not in ("proportional", "softmax"):
        raise ValueError(f"unknown norm {norm!r}")
    return normalise(entropies.select("domain", (F.exp("entropy") if norm == "softmax" else F.col("entropy")).alias("weight")))


def minimax(t: Table, steps: int = 200, eta: float = 0.5, smooth: float = 1e-3, rounds: int = 5, lr: float = 2.0, tol: float = 1e-3, start: np.ndarray | None = None) -> np.ndarray:
    """Worst-case reweighting by loss in excess of a reference, over rounds that start from the last one's weights.

    The reference is a unigram model fitted at the round's starting weights; the proxy starts flat, as from the reference every
    excess would be zero.
    """
    a = t.natural if start is None else start
    flat = np.full_like(a, 1 / len(a))
    for _ in range(rounds):
        ref = -(t.p * np.log(a @ t.p)).sum(1)
        logits, w, seen = np.zeros(t.p.shape[1]), flat.copy(), np.zeros_like(a)
        for _ in range(steps):
            q = softmax(logits)
            gap = np.maximum(-(t.p * np.log(q)).sum(1) - ref, 0)
            w = w * np.exp(eta * gap)
            w = (1 - smooth) * w / w.sum() + smooth * flat
            logits += lr * (w @ (t.p - q)) * t.p.shape[1] ** 0.5
            seen += w
        new = seen / seen.sum()
        moved = np.abs(new - a).sum() / 2
        a = new
        if moved < tol:
            break
    return a


def generalisation(t: Table, target: np.ndarray | None = None, steps: int = 200, eta: float = 1.0, mu: float = 0.05, lr: float = 1.0) -> np.ndarray:
    """Weights grow with how well a domain's gradient agrees with all domains' (or a target's) gradient; averaged over the steps."""
    logits, w, seen = np.zeros(t.p.shape[1]), np.full(len(t.names), 1 / len(t.names)), np.zeros(len(t.names))
    for _ in range(steps):
        q = softmax(logits)
        grad = q - t.p
        goal = grad.sum(0) if target is None else q - target
        w = w * np.exp(eta * (grad @ goal) / mu)
        w /= w.sum()
        logits -= lr * (w @ grad) * t.p.shape[1] ** 0.5
        seen += w
    return seen / steps


def trial_mixtures(t: Table, seed: int = 42, per_domain: int = 4) -> np.ndarray:
    """Corner-leaning, natural, uniform and random points of the simplex."""
    m = len(t.names)
    rng = np.random.default_rng(seed)
    corners = 0.7 * np.eye(m) + 0.3 / m
    return np.vstack([t.natural, np.full(m, 1 / m), corners, rng.dirichlet(np.ones(m), max(0, per_domain * m - m - 2))])


def trial_losses(counts: DataFrame, mixes: np.ndarray, volumes: tuple[float, ...] = (0.25, 0.5, 1.0), vocab: int = 1 << 10, smooth: float = 0.5) -> pd.DataFrame:
    """(trial, domain, share, volume, loss): held-out losses of a unigram proxy for each mixture and volume, from (domain, part, t, n).

    A proxy of volume s is counted on the documents of that slice, its domains weighed to their shares of as many tokens;
    counts mix linearly, so no trial passes over text. The loss is the cross entropy on the domain's held-out documents.
    """
    cells = counts.count()
    if cells > MAX_CELLS:
        raise ValueError(f"{cells} cells; hash the vocabulary into fewer buckets")
    pdf = counts.toPandas()
    names = sorted(pdf["domain"].unique())
    n = np.zeros((len(volumes) + 1, len(names), vocab))
    np.add.at(n, (pdf["part"].to_numpy() + 1, pdf["domain"].map({x: i for i, x in enumerate(names)}).to_numpy(), pdf["t"].to_numpy()), pdf["n"].to_numpy())
    held, rows = n[0] / np.maximum(n[0].sum(1, keepdims=True), 1), []
    slices = np.cumsum(n[1:], axis=0)
    for own, volume in zip(slices, volumes, strict=True):
        tokens = own.sum(1)
        rate = own / np.maximum(tokens[:, None], 1)
        for k, r in enumerate(mixes):
            q = (tokens.sum() * (r @ rate) + smooth) / (tokens.sum() + smooth * vocab)
            rows += [(k, name, float(r[d]), float(volume), float(-(held[d] * np.log(q)).sum())) for d, name in enumerate(names)]
    return pd.DataFrame(rows, columns=["trial", "domain", "share", "volume", "loss"])


def fit_bivariate(obs: DataFrame) -> DataFrame:
    """(domain, a, b, u, w, error) of loss = (u / s^b + w) / r^a, by a grid on a and b and least squares for u and w; one group per domain."""

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        r, s, y = (pdf[c].to_numpy(float) for c in ("share", "volume", "loss"))
        best = None
        for a in np.linspace(0.01, 1.0, 100):
            for b in np.linspace(0.05, 1.0, 20):
                x = np.stack([r**-a * s**-b, r**-a], axis=1)
                coef, *_ = np.linalg.lstsq(x, y, rcond=None)
                e = float(((x @ coef - y) ** 2).sum())
                if best is None or e < best[0]:
                    best = (e, a, b, *coef)
        return pd.DataFrame([(pdf["domain"].iloc[0], best[1], best[2], best[3], best[4], best[0])], columns=["domain", "a", "b", "u", "w", "error"])

    return obs.filter("share > 0").groupBy("domain").applyInPandas(fit, "domain string, a double, b double, u double, w double, error double")


def bivariate(fits: pd.DataFrame, volume: float = 1.0) -> np.ndarray:
    """Shares that minimise the summed fitted losses at a volume: r_d = (a_d K_d / mu)^(1 / (a_d + 1)), mu by bisection."""
    a, k = fits["a"].to_numpy(), np.maximum(fits["u"].to_numpy() / volume ** fits["b"].to_numpy() + fits["w"].to_numpy(), 1e-12)
    low, high = -60.0, 60.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if ((a * k / np.exp(mid)) ** (1 / (a + 1))).sum() > 1 else (low, mid)
    r = (a * k / np.exp(low)) ** (1 / (a + 1))
    return r / r.sum()


def fit_mixing_law(trials: DataFrame, names: list[str]) -> DataFrame:
    """(domain, c, k, t, error) of loss_d = c + k exp(sum t_j r_j), by a grid on c and log-linear least squares; rows have ``shares`` in the order of names."""

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        r, y = np.stack(pdf["shares"].to_numpy()), pdf["loss"].to_numpy(float)
        best = None
        for part in np.linspace(0.0, 0.99, 100):
            c = part * y.min()
            coef, *_ = np.linalg.lstsq(r, np.log(y - c), rcond=None)  # shares sum to 1, so log k lies within the t_j
            e = float(((c + np.exp(r @ coef) - y) ** 2).sum())
            if best is None or e < best[0]:
                best = (e, c, coef)
        return pd.DataFrame([(pdf["domain"].iloc[0], best[1], 1.0, best[2].tolist(), best[0])], columns=["domain", "c", "k", "t", "error"])

    return trials.groupBy("domain").applyInPandas(fit, "domain string, c double, k double, t array<double>, error double")


def mixing_law(fits: pd.DataFrame, names: list[str], start: np.ndarray, steps: int = 2000, eta: float = 0.05, starts: int = 4, seed: int = 42) -> np.ndarray:
    """Shares that minimise the summed fitted losses, by exponentiated gradient from several starting points."""
    fits = fits.set_index("domain").loc[names]
    t, k = np.stack(fits["t"].to_numpy()), fits["k"].to_numpy()
    rng, best = np.random.default_rng(seed), None
    for r in [start, np.full(len(names), 1 / len(names)), *rng.dirichlet(np.ones(len(names)), starts)]:
        r = np.maximum(r, 1e-9)
        for _ in range(steps):
            g = (k * np.exp(t @ r)) @ t
            r = r * np.exp(-eta * (g - g.min()) / (np.abs(g).max() + 1e-12))
            r /= r.sum()
        value = float((k * np.exp(t @ r)).sum())
        if best is None or value < best[0]:
            best = (value, r)
    return best[1]


BASELINES = ("natural", "minimax", "cond_entropy", "bivariate", "generalisation", "mixing_law")


def all_weights(spark: SparkSession, docs: DataFrame, vocab: int = 1 << 10, methods: tuple[str, ...] | None = None) -> dict[str, DataFrame]:
    """The six baselines' weights, or those of ``methods``, for a corpus of (doc_id, domain, text, n_tokens); only what they need is counted."""
    from . import domains, ngram
    from .corpus import stats

    asked, out = set(BASELINES if methods is None else methods), {}
    if "natural" in asked:
        out["natural"] = domains.natural(stats(docs))
    if "cond_entropy" in asked:
        out["cond_entropy"] = cond_entropy(ngram.conditional_entropy(docs))
    if asked & {"minimax", "bivariate", "generalisation", "mixing_law"}:
        t = table(ngram.domain_table(docs, vocab))
    if "minimax" in asked:
        out["minimax"] = frame(spark, t.names, minimax(t))
    if "generalisation" in asked:
        out["generalisation"] = frame(spark, t.names, generalisation(t))
    if asked & {"bivariate", "mixing_law"}:
        mixes = trial_mixtures(t)
        two = trial_losses(ngram.domain_parts(docs, vocab), mixes, vocab=vocab)
    if "bivariate" in asked:
        fits4 = fit_bivariate(spark.createDataFrame(two)).toPandas().set_index("domain").loc[t.names].reset_index()
        out["bivariate"] = frame(spark, t.names, bivariate(fits4))
    if "mixing_law" in asked:
        law_rows = [(r.domain, [float(x) for x in mixes[r.trial]], r.loss) for r in two[two["volume"] == 1.0].itertuples()]
        fits6 = fit_mixing_law(spark.createDataFrame(law_rows, "domain string, shares array<double>, loss double"), t.names).toPandas()
        out["mixing_law"] = frame(spark, t.names, mixing_law(fits6, t.names, t.natural))
    return {m: out[m] for m in BASELINES if m in out}
