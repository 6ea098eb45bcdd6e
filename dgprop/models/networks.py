"""Encoders of sequences, dense heads, and how they are trained.

Parameters are arrays by name.  ``Adam`` works on the sums of gradients over rows,
so the rows can be in one task or spread over partitions.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame

from dgprop.models.autograd import Var, concat, joint, stack

Params = dict[str, np.ndarray]
#: Columns of rows.
Arrays = dict[str, np.ndarray]


def _init(rng: np.random.Generator, *shape: int) -> np.ndarray:
    return rng.normal(0, 1 / np.sqrt(shape[0]), shape)


def dense_params(rng: np.random.Generator, sizes: list[int], name: str = "mlp") -> Params:
    out = {}
    for i, (a, b) in enumerate(zip(sizes[:-1], sizes[1:], strict=True)):
        out[f"{name}{i}_w"], out[f"{name}{i}_b"] = _init(rng, a, b), np.zeros(b)
    return out


def dense(p: dict[str, Var], x: Var, layers: int, name: str = "mlp") -> Var:
    for i in range(layers):
        x = x @ p[f"{name}{i}_w"] + p[f"{name}{i}_b"]
        if i + 1 < layers:
            x = x.relu()
    return x


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def lstm_params(rng: np.random.Generator, d: int, h: int) -> Params:
    return {"cell_w": _init(rng, d + h, 4 * h), "cell_b": np.zeros(4 * h)}


def lstm(p: dict[str, Var], x: Var, mask: np.ndarray) -> Var:
    """The last state over (rows, steps, places); where the mask is 0 the state stays."""
    w, bias = p["cell_w"].value, p["cell_b"].value
    k = len(bias) // 4
    h, c, past = np.zeros((len(x.value), k)), np.zeros((len(x.value), k)), []
    for t in range(x.shape[1]):
        both, m = np.concatenate((h, x.value[:, t]), axis=1), mask[:, t : t + 1]
        z = both @ w + bias
        gates, new = _sigmoid(z[:, : 3 * k]), np.tanh(z[:, 3 * k :])
        into, forget, out = gates[:, :k], gates[:, k : 2 * k], gates[:, 2 * k :]
        c_new = forget * c + into * new
        bent = np.tanh(c_new)
        past.append((both, m, gates, new, c, bent))
        c, h = c_new * m + c * (1 - m), out * bent * m + h * (1 - m)

    def back(g: np.ndarray) -> tuple[np.ndarray, ...]:
        dw, db, dx, dh, dc = np.zeros_like(w), np.zeros_like(bias), np.zeros_like(x.value), g, np.zeros_like(g)
        for t in range(len(past) - 1, -1, -1):
            both, m, gates, new, c, bent = past[t]
            into, forget, out = gates[:, :k], gates[:, k : 2 * k], gates[:, 2 * k :]
            dhm = dh * m
            dcm = dc * m + dhm * out * (1 - bent * bent)
            dz = np.concatenate((np.concatenate((dcm * new, dcm * c, dhm * bent), axis=1) * (gates * (1 - gates)), dcm * into * (1 - new * new)), axis=1)
            dw += both.T @ dz
            db += dz.sum(axis=0)
            d = dz @ w.T
            dh, dc, dx[:, t] = d[:, :k] + dh * (1 - m), dcm * forget + dc * (1 - m), d[:, k:]
        return dw, db, dx

    return joint(h, [p["cell_w"], p["cell_b"], x], back)


def gru_params(rng: np.random.Generator, d: int, h: int) -> Params:
    return {"gate_w": _init(rng, d + h, 2 * h), "gate_b": np.zeros(2 * h), "new_w": _init(rng, d + h, h), "new_b": np.zeros(h)}


def gru(p: dict[str, Var], x: Var, mask: np.ndarray) -> Var:
    """The last state, like ``gru_step`` over the steps."""
    names = ("gate_w", "gate_b", "new_w", "new_b")
    gate_w, gate_b, new_w, new_b = (p[n].value for n in names)
    k = len(new_b)
    h, past = np.zeros((len(x.value), k)), []
    for t in range(x.shape[1]):
        both, m = np.concatenate((h, x.value[:, t]), axis=1), mask[:, t : t + 1]
        gates = _sigmoid(both @ gate_w + gate_b)
        update, reset = gates[:, :k], gates[:, k:]
        kept = np.concatenate((reset * h, x.value[:, t]), axis=1)
        new = np.tanh(kept @ new_w + new_b)
        past.append((both, m, gates, kept, new))
        h = (update * h + (1 - update) * new) * m + h * (1 - m)

    def back(g: np.ndarray) -> tuple[np.ndarray, ...]:
        made, dx, dh = [np.zeros_like(p[n].value) for n in names], np.zeros_like(x.value), g
        for t in range(len(past) - 1, -1, -1):
            both, m, gates, kept, new = past[t]
            h, update, reset = both[:, :k], gates[:, :k], gates[:, k:]
            dhm = dh * m
            dz = dhm * (1 - update) * (1 - new * new)
            d = dz @ new_w.T
            dg = np.concatenate((dhm * (h - new), d[:, :k] * h), axis=1) * (gates * (1 - gates))
            e = dg @ gate_w.T
            for total, part in zip(made, (both.T @ dg, dg.sum(axis=0), kept.T @ dz, dz.sum(axis=0)), strict=True):
                total += part
            dh, dx[:, t] = dhm * update + dh * (1 - m) + d[:, :k] * reset + e[:, :k], d[:, k:] + e[:, k:]
        return *made, dx

    return joint(h, [*(p[n] for n in names), x], back)


def gru_step(p: dict[str, Var], h: Var, x: Var, mask: np.ndarray | float = 1.0) -> Var:
    k = p["new_b"].shape[0]
    g = (concat([h, x]) @ p["gate_w"] + p["gate_b"]).sigmoid()
    update, reset = g[:, :k], g[:, k:]
    new = (concat([reset * h, x]) @ p["new_w"] + p["new_b"]).tanh()
    moved = update * h + (1 - update) * new
    return moved * mask + h * (1 - mask)


def transformer_params(rng: np.random.Generator, d: int, h: int) -> Params:
    out = {f"{n}_w": _init(rng, h, h) for n in ("query", "key", "value", "mixed")}
    out |= {"in_w": _init(rng, d, h), "in_b": np.zeros(h)}
    return out | dense_params(rng, [h, 2 * h, h], "feed") | {f"norm{i}_{k}": (np.ones(h) if k == "a" else np.zeros(h)) for i in (0, 1) for k in "ab"}


def _norm(x: Var, a: Var, b: Var) -> Var:
    centred = x - x.mean(-1, True)
    return centred * ((centred * centred).mean(-1, True) + 1e-6) ** -0.5 * a + b


def transformer(p: dict[str, Var], x: Var, mask: np.ndarray, heads: int = 2) -> Var:
    """One encoder layer with causal attention; the state at the last step."""
    n, steps, _ = x.shape
    h = p["in_b"].shape[0]
    rate = 1 / 100 ** (np.arange(h) // 2 * 2 / h)
    angle = np.arange(steps)[:, None] * rate[None, :]
    x = x @ p["in_w"] + p["in_b"] + np.where(np.arange(h) % 2 == 0, np.sin(angle), np.cos(angle))
    q, k, v = x @ p["query_w"], x @ p["key_w"], x @ p["value_w"]
    hidden = np.where((np.arange(steps)[None, :] > np.arange(steps)[:, None])[None] | (mask[:, None, :] == 0), -1e9, 0.0)
    size, parts = h // heads, []
    for i in range(heads):
        at = slice(i * size, (i + 1) * size)
        score = q[:, :, at] @ k[:, :, at].swap() * (1 / np.sqrt(size)) + hidden
        parts.append(score.softmax() @ v[:, :, at])
    x = _norm(x + concat(parts) @ p["mixed_w"], p["norm0_a"], p["norm0_b"])
    x = _norm(x + dense(p, x, 2, "feed"), p["norm1_a"], p["norm1_b"])
    return x[:, steps - 1]


ENCODERS: dict[str, tuple[Callable, Callable]] = {"lstm": (lstm_params, lstm), "gru": (gru_params, gru), "transformer": (transformer_params, transformer)}


def combine(a: Var, b: Var, kind: str = "concat") -> Var:
    """Of two nodes' states one for the pair."""
    if kind == "concat":
        return concat([a, b])
    if kind == "hadamard":
        return a * b
    if kind == "average":
        return (a + b) * 0.5
    if kind == "difference":
        return (a - b) * (a - b)
    raise ValueError(kind)


def values_of(column: pd.Series) -> np.ndarray:
    """Rows of lists of equal sizes, nested or not, as one array with a row for each."""
    rows = list(column)
    if rows and isinstance(rows[0], np.ndarray) and rows[0].dtype != object:
        return np.concatenate(rows).reshape(len(rows), *rows[0].shape)
    return np.array([np.stack(list(r)) if len(r) and np.ndim(r[0]) else r for r in rows], float)


@dataclass
class LinkModel:
    """An encoder of both ends' sequences, a way to combine them, and a dense head with one logit."""

    kind: str
    d: int
    h: int
    how: str = "concat"
    #: What changes are multiplied by, so that they are of size 1 in the training rows.
    scale: float = 1.0

    def init(self, seed: int) -> Params:
        rng = np.random.default_rng(seed)
        return ENCODERS[self.kind][0](rng, self.d, self.h) | dense_params(rng, [2 * self.h if self.how == "concat" else self.h, self.h, 1])

    def arrays(self, rows: pd.DataFrame) -> Arrays:
        """The columns of rows; sequences may be flat."""
        out = {f"x{side}": values_of(rows[f"x{side}"]).reshape(len(rows), -1, self.d) for side in ("a", "b") if len(rows)}
        return out | {c: values_of(rows[c]) for c in ("ma", "mb") if len(rows)} | {"label": rows["label"].to_numpy()}

    def state(self, p: dict[str, Var], x: np.ndarray, mask: np.ndarray) -> Var:
        return ENCODERS[self.kind][1](p, Var(x * self.scale), mask.astype(float))

    def logits(self, p: dict[str, Var], batch: Arrays) -> Var:
        n = len(batch["xa"])
        ends = self.state(p, *(np.concatenate((batch[f"{c}a"], batch[f"{c}b"])) for c in "xm"))
        return dense(p, combine(ends[:n], ends[n:], self.how), 2)[:, 0]

    def encode(self, p: Params, x: np.ndarray, mask: np.ndarray) -> np.ndarray:
        """The states of sequences."""
        return self.state({k: Var(v) for k, v in p.items()}, x, mask).value

    def head(self, p: Params, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The scores of pairs of states."""
        known = {k: Var(v) for k, v in p.items()}
        return dense(known, combine(Var(a), Var(b), self.how), 2)[:, 0].sigmoid().value

    def loss(self, p: dict[str, Var], batch: Arrays) -> Var:
        return binary_loss(self.logits(p, batch), batch["label"])

    def scores(self, p: Params, batch: pd.DataFrame) -> np.ndarray:
        return self.logits({k: Var(v) for k, v in p.items()}, self.arrays(batch)).sigmoid().value


@dataclass
class ClassModel:
    """Dense layers with softmax, or with independent sigmoids for several labels."""

    sizes: list[int]
    multi_label: bool = False

    def init(self, seed: int) -> Params:
        return dense_params(np.random.default_rng(seed), self.sizes)

    def arrays(self, rows: pd.DataFrame) -> Arrays:
        return {"x": values_of(rows["x"]), "label": values_of(rows["label"]) if self.multi_label else rows["label"].to_numpy()}

    def logits(self, p: dict[str, Var], batch: Arrays) -> Var:
        return dense(p, Var(batch["x"]), len(self.sizes) - 1)

    def loss(self, p: dict[str, Var], batch: Arrays) -> Var:
        z = self.logits(p, batch)
        if self.multi_label:
            return binary_loss(z, batch["label"])
        chance = z.softmax()[np.arange(len(batch["label"])), batch["label"].astype(int)]
        return -((chance + 1e-12).log()).sum()

    def scores(self, p: Params, batch: pd.DataFrame) -> np.ndarray:
        z = self.logits({k: Var(v) for k, v in p.items()}, {"x": values_of(batch["x"])})
        return (z.sigmoid() if self.multi_label else z.softmax()).value


def binary_loss(logits: Var, y: np.ndarray) -> Var:
    p = logits.sigmoid()
    return -(((p + 1e-12).log() * y) + ((1 - p + 1e-12).log() * (1 - y))).sum()


def gradient(model, params: Params, batch: pd.DataFrame | Arrays) -> tuple[float, Params]:
    """Loss and gradients, summed over the rows."""
    if isinstance(batch, pd.DataFrame):
        batch = model.arrays(batch)
    p = {k: Var(v) for k, v in params.items()}
    loss = model.loss(p, batch)
    loss.backward()
    return float(loss.value), {k: v.grad if v.grad is not None else np.zeros_like(v.value) for k, v in p.items()}


class Adam:
    def __init__(self, params: Params, rate: float) -> None:
        self.rate, self.t = rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, params: Params, grads: Params) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            params[k] = params[k] - self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


def _epoch(model, params: Params, adam: Adam, arrays: Arrays, order: np.ndarray, batch: int) -> None:
    for k in range(0, len(order), batch):
        at = order[k : k + batch]
        _, g = gradient(model, params, {n: v[at] for n, v in arrays.items()})
        adam.step(params, {n: v / len(at) for n, v in g.items()})


def fit_rows(model, rows: pd.DataFrame | Arrays, epochs: int, batch: int, rate: float, seed: int) -> Params:
    """Mini-batches in one process."""
    params, rng = model.init(seed), np.random.default_rng(seed)
    adam, arrays = Adam(params, rate), model.arrays(rows) if isinstance(rows, pd.DataFrame) else rows
    for _ in range(epochs):
        _epoch(model, params, adam, arrays, rng.permutation(len(arrays["label"])), batch)
    return params


def fit_dealt(model, packed: DataFrame, epochs: int, batch: int, rate: float, seed: int) -> Params:
    """Mini-batches over all rows of all parts (of ``fitting.dealt``).

    Each part goes through its own rows; after an epoch the parameters and Adam's
    means are averaged by the number of rows, and all parts go on from there.  One
    part is the same as ``fit_rows``.
    """
    params = model.init(seed)
    adam, names = Adam(params, rate), sorted(params)
    # One part needs no averages and goes through all epochs at once.
    turns = [(0, epochs)] if packed.count() == 1 else [(epoch, epoch + 1) for epoch in range(epochs)]
    for low, high in turns:
        now = pickle.dumps((params, adam))

        def work(batches: Iterator[pa.RecordBatch], now: bytes = now, low: int = low, high: int = high) -> Iterator[pa.RecordBatch]:
            for held in batches:
                for deal, blob in zip(held.column("deal").to_pylist(), held.column("arrays"), strict=True):
                    arrays = pickle.loads(blob.as_buffer())
                    mine, own = pickle.loads(now)
                    rng = np.random.default_rng([seed, deal] if deal else seed)
                    for k in range(high):
                        order = rng.permutation(len(arrays["label"]))
                        if k >= low:
                            _epoch(model, mine, own, arrays, order, batch)
                    flat = np.concatenate([of[k].ravel() for of in (mine, own.m, own.v) for k in names])
                    yield pa.RecordBatch.from_pydict({"deal": pa.array([deal], pa.int32()), "n": [len(order)], "t": [own.t], "flat": pa.array([flat.tobytes()], pa.binary())})

        # One row for each part, as large as the model.
        got = sorted(packed.mapInArrow(work, "deal int, n bigint, t bigint, flat binary").collect())
        n = sum(r["n"] for r in got)
        flat, at = sum(np.frombuffer(r["flat"]) * (r["n"] / n) for r in got), 0
        for of in (params, adam.m, adam.v):
            for k in names:
                of[k] = flat[at : at + of[k].size].reshape(of[k].shape)
                at += of[k].size
        adam.t = max(r["t"] for r in got)
    return params


def fit_partitions(model, rows: DataFrame, epochs: int, rate: float, seed: int) -> Params:
    """One step for each epoch from the gradients that partitions sum up; rows never leave them."""
    params = model.init(seed)
    adam, names = Adam(params, rate), sorted(params)
    for _ in range(epochs):
        now = dict(params)

        def work(parts: Iterator[pd.DataFrame], now: Params = now) -> Iterator[pd.DataFrame]:
            total, n = {k: np.zeros_like(v) for k, v in now.items()}, 0
            for part in parts:
                if len(part):
                    _, g = gradient(model, now, part)
                    total, n = {k: total[k] + g[k] for k in total}, n + len(part)
            yield pd.DataFrame({"n": [n], "g": [np.concatenate([total[k].ravel() for k in names]).tobytes()]})

        got = rows.mapInPandas(work, "n bigint, g binary").collect()  # one row for each partition
        n, flat = sum(r["n"] for r in got), sum(np.frombuffer(r["g"]) for r in got)
        at, grads = 0, {}
        for k in names:
            grads[k] = flat[at : at + params[k].size].reshape(params[k].shape) / max(n, 1)
            at += params[k].size
        adam.step(params, grads)
    return params


def states(model_kind: str, params: Params, x: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """Final states of sequences."""
    return ENCODERS[model_kind][1]({k: Var(v) for k, v in params.items()}, Var(x), mask).value


__all__ = ["ENCODERS", "Adam", "ClassModel", "LinkModel", "combine", "fit_dealt", "fit_partitions", "fit_rows", "gradient", "gru_step", "stack", "states"]
