"""Gradient of the energy and the parameter update."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.ansatz import Model, Params
from detspark.functions.schema import ProblemSpec


def gradient(local: DataFrame, energy: float, norm: float, model: Model, spec: ProblemSpec, fan_in: int = 64) -> Params:
    """2 Re sum_i p_i conj(E_i - E) dlog(psi_i), from local energies ``(s*, num_re[, num_im], psi_re[, psi_im], wgt)``.

    Each task sends one row as large as the parameters; rows are added in ``fan_in`` groups before the last sum, so the
    driver gets at most that many.
    """
    held = local.sparkSession.sparkContext.broadcast(model)
    names, m, complex_ = spec.source_names, spec.m, "psi_im" in local.columns
    columns = [*names, "num_re", "psi_re", "wgt", *(["num_im", "psi_im"] if complex_ else [])]
    layout = sorted((k, v.shape, v.size) for k, v in model.params.items())

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if not batch.num_rows:
                continue
            get = lambda c: batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False).astype(float)  # noqa: B023, E731
            words = np.stack([batch.column(batch.schema.get_field_index(c)).to_numpy() for c in names], 1)
            psi, num, wgt = get("psi_re"), get("num_re"), get("wgt")
            if complex_:
                psi, num = psi + 1j * get("psi_im"), num + 1j * get("num_im")
            # p_i (E_i - E) = conj(psi_i) (num_i - E psi_i) / norm, without dividing by psi_i
            f = np.conj(psi) * num / norm - energy * wgt / norm
            # 2 Re[conj(f) (dlog|psi| + i dphase)]
            grads = held.value.backward(bits.to_bits(words, m), 2 * np.real(f), 2 * np.imag(f))
            flat = np.concatenate([grads[k].ravel() for k, _, _ in layout])
            total = flat if total is None else total + flat
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["g"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            for value in batch.column(0):
                got = np.frombuffer(value.as_buffer())
                total = got if total is None else total + got
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["g"])

    rows = local.select(*columns).mapInArrow(task, "g binary").repartition(fan_in, F.xxhash64("g")).mapInArrow(add, "g binary").collect()
    flat = sum((np.frombuffer(r["g"]) for r in sorted(rows, key=lambda r: r["g"])), np.zeros(sum(n for _, _, n in layout)))
    out, at = {}, 0
    for k, shape, size in layout:
        out[k] = flat[at : at + size].reshape(shape)
        at += size
    return out


class AdamW:
    """Moment estimates with decoupled weight decay."""

    def __init__(self, lr: float = 3e-4, beta1: float = 0.9, beta2: float = 0.999, eps: float = 1e-8, decay: float = 0.01) -> None:
        self.lr, self.beta1, self.beta2, self.eps, self.decay = lr, beta1, beta2, eps, decay
        self.t, self.first, self.second = 0, {}, {}

    def step(self, params: Params, grads: Params) -> Params:
        self.t += 1
        out = {}
        for k, p in params.items():
            g = grads[k]
            a = self.first[k] = self.beta1 * self.first.get(k, 0.0) + (1 - self.beta1) * g
            b = self.second[k] = self.beta2 * self.second.get(k, 0.0) + (1 - self.beta2) * g * g
            a_hat, b_hat = a / (1 - self.beta1**self.t), b / (1 - self.beta2**self.t)
            out[k] = p * (1 - self.lr * self.decay) - self.lr * a_hat / (np.sqrt(b_hat) + self.eps)
        return out


def dense_energy(model: Model, words: np.ndarray, h: np.ndarray, m: int) -> float:
    """Energy by matrix, for small checks."""
    log, phase = model.forward(bits.to_bits(words, m))
    psi = np.exp(log - log.max() + 1j * phase)
    return float((np.conj(psi) @ h @ psi / (np.conj(psi) @ psi)).real)


def dense_gradient(model: Model, words: np.ndarray, h: np.ndarray, m: int) -> Params:
    """The same gradient by matrix: a twin of ``gradient`` for small spaces."""
    x = bits.to_bits(words, m)
    log, phase = model.forward(x)
    psi = np.exp(log - log.max() + 1j * phase)
    norm = float((np.abs(psi) ** 2).sum())
    energy = float((np.conj(psi) @ h @ psi).real / norm)
    f = np.conj(psi) * (h @ psi) / norm - energy * np.abs(psi) ** 2 / norm
    return model.backward(x, 2 * f.real, 2 * f.imag)
