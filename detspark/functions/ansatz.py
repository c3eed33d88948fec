"""Amplitude models: configurations to log |psi| and phase, with gradients of both.

Models are plain arrays in a dict of parameters, so they are broadcast as they are and run in Arrow batches.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.schema import PARAMS

Params = dict[str, np.ndarray]


class Model:
    """``forward`` gives (log |psi|, phase) of an occupation matrix; ``backward`` the gradient of sum(u * log|psi| + v * phase)."""

    params: Params

    def forward(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        raise NotImplementedError

    def backward(self, x: np.ndarray, u: np.ndarray, v: np.ndarray) -> Params:
        raise NotImplementedError

    def size(self) -> int:
        return sum(p.size for p in self.params.values())


def closed_form(words: list[Column]) -> Column:
    """Whole-number amplitude of one-word keys, for exact checks: (w * 7919 mod 1009) - 504."""
    return (words[0] * 7919 % 1009 - 504).cast("long")


@dataclass
class Tabular(Model):
    """One number per listed configuration (log |psi| and phase); others get ``floor``."""

    words: np.ndarray
    params: Params
    floor: float = -30.0

    @staticmethod
    def start(words: np.ndarray, seed: int = 0) -> Tabular:
        rng = np.random.default_rng(seed)
        return Tabular(words, {"log": rng.normal(0, 0.1, len(words)), "phase": rng.normal(0, 0.1, len(words))})

    def _rows(self, x: np.ndarray) -> np.ndarray:
        known = {tuple(w): i for i, w in enumerate(self.words.tolist())}
        return np.array([known.get(tuple(w), -1) for w in bits.from_bits(x).tolist()])

    def forward(self, x):
        at = self._rows(x)
        return np.where(at >= 0, self.params["log"][at], self.floor), np.where(at >= 0, self.params["phase"][at], 0.0)

    def backward(self, x, u, v):
        at = self._rows(x)
        ok = at >= 0
        n = len(self.words)
        return {"log": np.bincount(at[ok], u[ok], n), "phase": np.bincount(at[ok], v[ok], n)}


@dataclass
class ClosedForm(Model):
    """The whole-number amplitude of ``closed_form`` as a model without anything to learn: what the loop does with it can be checked exactly."""

    params: Params = field(default_factory=lambda: {"none": np.zeros(1)})

    def forward(self, x):
        value = bits.from_bits(x)[:, 0] * 7919 % 1009 - 504
        with np.errstate(divide="ignore"):
            return np.log(np.abs(value).astype(float)), np.where(value < 0, np.pi, 0.0)

    def backward(self, x, u, v):
        return {"none": np.zeros(1)}


@dataclass
class Rbm(Model):
    """Restricted Boltzmann form over signs s = 2 x - 1: log|psi| = a.s + sum log 2 cosh(b + W s), phase = c.s."""

    params: Params

    @staticmethod
    def start(m: int, hidden: int, seed: int = 0, scale: float = 0.1) -> Rbm:
        rng = np.random.default_rng(seed)
        return Rbm({"a": rng.normal(0, scale, m), "b": rng.normal(0, scale, hidden), "w": rng.normal(0, scale, (hidden, m)), "c": rng.normal(0, scale, m)})

    def forward(self, x):
        s, p = 2.0 * x - 1.0, self.params
        t = s @ p["w"].T + p["b"]
        return s @ p["a"] + np.logaddexp(t, -t).sum(1), s @ p["c"]

    def backward(self, x, u, v):
        s, p = 2.0 * x - 1.0, self.params
        t = np.tanh(s @ p["w"].T + p["b"]) * u[:, None]
        return {"a": u @ s, "b": t.sum(0), "w": t.T @ s, "c": v @ s}

    def column(self, words: list[Column], m: int) -> Column:
        """log |psi| as an expression in the JVM."""
        p = self.params
        sign = lambda i: (F.getbit(words[i // 63], F.lit(i % 63)) * 2 - 1).cast("double")
        signs = [sign(i) for i in range(m)]
        out = sum((signs[i] * float(p["a"][i]) for i in range(m)), F.lit(0.0))
        for h in range(len(p["b"])):
            t = sum((signs[i] * float(p["w"][h, i]) for i in range(m)), F.lit(float(p["b"][h])))
            out = out + F.abs(t) + F.log1p(F.exp(-2 * F.abs(t)))
        return out


@dataclass
class PhaseMlp:
    """Phase from the signs, ``layers`` layers of tanh units."""

    params: Params
    layers: int

    @staticmethod
    def start(m: int, hidden: int = 64, layers: int = 4, seed: int = 1) -> PhaseMlp:
        rng, sizes = np.random.default_rng(seed), [m, *[hidden] * (layers - 1), 1]
        p: Params = {}
        for k in range(layers):
            p[f"m{k}"] = rng.normal(0, 1 / np.sqrt(sizes[k]), (sizes[k], sizes[k + 1]))
            p[f"o{k}"] = np.zeros(sizes[k + 1])
        return PhaseMlp(p, layers)

    def forward(self, x: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        held = [2.0 * x - 1.0]
        for k in range(self.layers):
            y = held[-1] @ self.params[f"m{k}"] + self.params[f"o{k}"]
            held.append(np.tanh(y) if k < self.layers - 1 else y)
        return held[-1][:, 0], held

    def backward(self, held: list[np.ndarray], v: np.ndarray) -> Params:
        out: Params = {}
        d = v[:, None]
        for k in range(self.layers - 1, -1, -1):
            if k < self.layers - 1:
                d = d * (1 - held[k + 1] ** 2)
            out[f"m{k}"], out[f"o{k}"] = held[k].T @ d, d.sum(0)
            d = d @ self.params[f"m{k}"].T
        return out


def _norm(x: np.ndarray, g: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, tuple]:
    mu, var = x.mean(-1, keepdims=True), x.var(-1, keepdims=True)
    r = 1 / np.sqrt(var + 1e-5)
    h = (x - mu) * r
    return h * g + b, (h, r, g)


def _norm_back(d: np.ndarray, kept: tuple) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    h, r, g = kept
    axes = tuple(range(d.ndim - 1))
    dh = d * g
    dx = r * (dh - dh.mean(-1, keepdims=True) - h * (dh * h).mean(-1, keepdims=True))
    return dx, (d * h).sum(axes), d.sum(axes)


@dataclass
class Transformer(Model):
    """Autoregressive model over orbitals with a fixed number of ones, plus a phase network.

    Token t is the occupation before orbital t (a start token at 0); causal blocks give two logits per orbital; choices that
    would break the number of ones are masked.  |psi|² is the product of the conditionals and so sums to 1 over the space.
    """

    m: int
    n: int
    width: int
    layers: int
    heads: int
    params: Params
    phase: PhaseMlp = field(repr=False)

    @staticmethod
    def start(m: int, n: int, width: int = 32, layers: int = 4, heads: int = 4, hidden: int = 64, seed: int = 0) -> Transformer:
        rng, p = np.random.default_rng(seed), {}
        p["tok"], p["pos"] = rng.normal(0, 0.1, (3, width)), rng.normal(0, 0.1, (m, width))
        for k in range(layers):
            for name, shape in (("qkv", (width, 3 * width)), ("out", (width, width)), ("up", (width, 4 * width)), ("down", (4 * width, width))):
                p[f"{name}{k}"] = rng.normal(0, 1 / np.sqrt(shape[0]), shape) * (0.5 if name in ("out", "down") else 1.0)
            for name, size in (("bqkv", 3 * width), ("bout", width), ("bup", 4 * width), ("bdown", width), ("b1_", width), ("b2_", width)):
                p[f"{name}{k}"] = np.zeros(size)
            p[f"g1_{k}"], p[f"g2_{k}"] = np.ones(width), np.ones(width)
        p["gf"], p["bf"], p["head"], p["bhead"] = np.ones(width), np.zeros(width), rng.normal(0, 0.1, (width, 2)), np.zeros(2)
        mlp = PhaseMlp.start(m, hidden, 4, seed + 1)
        return Transformer(m, n, width, layers, heads, p | mlp.params, mlp)

    def _phase(self) -> PhaseMlp:
        return PhaseMlp({k: self.params[k] for k in self.phase.params}, self.phase.layers)

    def _logits(self, x: np.ndarray) -> tuple[np.ndarray, tuple]:
        p, (b, t), w, h = self.params, x.shape, self.width, self.heads
        tokens = np.concatenate([np.full((b, 1), 2), x[:, :-1]], 1).astype(int)
        y = p["tok"][tokens] + p["pos"][:t]
        causal = np.triu(np.full((t, t), -1e30), 1)
        kept = []
        for k in range(self.layers):
            a, n1 = _norm(y, p[f"g1_{k}"], p[f"b1_{k}"])
            qkv = (a @ p[f"qkv{k}"] + p[f"bqkv{k}"]).reshape(b, t, 3, h, w // h).transpose(2, 0, 3, 1, 4)
            q, key, v = qkv
            s = q @ key.swapaxes(-1, -2) / np.sqrt(w // h) + causal
            s = np.exp(s - s.max(-1, keepdims=True))
            s /= s.sum(-1, keepdims=True)
            o = (s @ v).transpose(0, 2, 1, 3).reshape(b, t, w)
            y1 = y + o @ p[f"out{k}"] + p[f"bout{k}"]
            c, n2 = _norm(y1, p[f"g2_{k}"], p[f"b2_{k}"])
            u = c @ p[f"up{k}"] + p[f"bup{k}"]
            act = np.tanh(u)
            kept.append((a, n1, q, key, v, s, o, c, n2, act))
            y = y1 + act @ p[f"down{k}"] + p[f"bdown{k}"]
        z, nf = _norm(y, p["gf"], p["bf"])
        return z @ p["head"] + p["bhead"], (tokens, kept, z, nf)

    def _allowed(self, x: np.ndarray) -> np.ndarray:
        """Which of 0 and 1 may come next at each orbital, given what came before."""
        ones = np.cumsum(x, 1) - x
        t = np.arange(x.shape[1])
        zero = (t - ones) < (self.m - self.n)
        return np.stack([zero, ones < self.n], -1)

    def conditionals(self, x: np.ndarray) -> np.ndarray:
        """Probability of a one at each orbital after the ones before it."""
        z, _ = self._logits(x)
        z = np.where(self._allowed(x), z, -1e30)
        z = np.exp(z - z.max(-1, keepdims=True))
        return z[..., 1] / z.sum(-1)

    def _log(self, x: np.ndarray) -> tuple[np.ndarray, tuple]:
        z, kept = self._logits(x)
        z = np.where(self._allowed(x), z, -1e30)
        top = z.max(-1, keepdims=True)
        total = np.log(np.exp(z - top).sum(-1, keepdims=True)) + top
        chosen = np.take_along_axis(z, x[..., None].astype(int), -1)
        return 0.5 * (chosen - total)[..., 0].sum(1), (np.exp(z - total), kept)

    def forward(self, x):
        return self._log(x)[0], self._phase().forward(x)[0]

    def backward(self, x, u, v):
        p, (b, t), w, h = self.params, x.shape, self.width, self.heads
        _, (prob, (tokens, kept, z, nf)) = self._log(x)
        dz = -prob
        np.put_along_axis(dz, x[..., None].astype(int), np.take_along_axis(dz, x[..., None].astype(int), -1) + 1, -1)
        dz = np.where(self._allowed(x), dz, 0.0) * 0.5 * u[:, None, None]
        g: Params = {"head": np.einsum("btw,btk->wk", z, dz), "bhead": dz.sum((0, 1))}
        dy, g["gf"], g["bf"] = _norm_back(dz @ p["head"].T, nf)
        for k in range(self.layers - 1, -1, -1):
            a, n1, q, key, val, s, o, c, n2, act = kept[k]
            g[f"down{k}"], g[f"bdown{k}"] = np.einsum("bti,btj->ij", act, dy), dy.sum((0, 1))
            du = (dy @ p[f"down{k}"].T) * (1 - act**2)
            g[f"up{k}"], g[f"bup{k}"] = np.einsum("bti,btj->ij", c, du), du.sum((0, 1))
            dn, g[f"g2_{k}"], g[f"b2_{k}"] = _norm_back(du @ p[f"up{k}"].T, n2)
            dy1 = dy + dn
            g[f"out{k}"], g[f"bout{k}"] = np.einsum("bti,btj->ij", o, dy1), dy1.sum((0, 1))
            do = (dy1 @ p[f"out{k}"].T).reshape(b, t, h, w // h).transpose(0, 2, 1, 3)
            dv = s.swapaxes(-1, -2) @ do
            ds = do @ val.swapaxes(-1, -2)
            ds = s * (ds - (ds * s).sum(-1, keepdims=True)) / np.sqrt(w // h)
            dqkv = np.stack([ds @ key, ds.swapaxes(-1, -2) @ q, dv]).transpose(1, 3, 0, 2, 4).reshape(b, t, 3 * w)
            g[f"qkv{k}"], g[f"bqkv{k}"] = np.einsum("bti,btj->ij", a, dqkv), dqkv.sum((0, 1))
            dn, g[f"g1_{k}"], g[f"b1_{k}"] = _norm_back(dqkv @ p[f"qkv{k}"].T, n1)
            dy = dy1 + dn
        g["pos"] = np.zeros_like(p["pos"])
        g["pos"][:t] = dy.sum(0)
        g["tok"] = np.zeros_like(p["tok"])
        np.add.at(g["tok"], tokens, dy)
        mlp = self._phase()
        return g | mlp.backward(mlp.forward(x)[1], v)


def save(params: Params, spark, iteration: int = 0) -> DataFrame:
    """Parameters as rows; they can be written and read like any table."""
    rows = [(iteration, k, list(v.shape), v.ravel().tolist()) for k, v in sorted(params.items())]
    return spark.createDataFrame(rows, PARAMS)


def restore(rows: DataFrame, iteration: int | None = None) -> Params:
    """Parameters of an iteration, by default the latest."""
    if iteration is None:
        iteration = rows.agg(F.max("iter")).first()[0]
    return {r["name"]: np.array(r["data"]).reshape(r["shape"]) for r in rows.where(F.col("iter") == iteration).collect()}
