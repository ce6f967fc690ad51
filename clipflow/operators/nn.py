"""The network's layers as NumPy kernels, their gradients, configurations, training by data-parallel steps, and models.

Arrays are (T, H, W, C) for clips and (T, D) for sequences. Kernels run inside Arrow batches; at the paper's sizes one
clip's activations fit a task, which is what bounds them.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from clipflow.operators import ctc
from clipflow.sources.tables import written

Params = dict[str, np.ndarray]

# ---- configurations: rows (layer, kind, k_t, k_s, c_in, c_out, stride, dilation)


def conv_rows(filters: list[int], channels: int = 1, k_t: int = 3, k_s: int = 3, stride: int = 1) -> list[tuple]:
    return [(i, "conv3d", k_t, k_s, c_in, c_out, stride, 1) for i, (c_in, c_out) in enumerate(zip([channels, *filters], filters))]


def config_full(filters: tuple[int, ...] = (4, 4, 8, 8, 8), hidden: int = 768, inputs: int = 512, symbols: int = 42) -> list[tuple]:
    rows = conv_rows(list(filters))
    widths = [inputs, 2 * hidden, 2 * hidden]
    rows += [(len(rows) + i, "bilstm", 1, 1, d, hidden, 1, 1) for i, d in enumerate(widths)]
    return [*rows, (len(rows), "dense", 1, 1, 2 * hidden, symbols, 1, 1)]


def config_small(filters: tuple[int, ...] = (4, 8, 8), hidden: int = 256, inputs: int = 512, symbols: int = 42) -> list[tuple]:
    rows = conv_rows(list(filters))
    rows += [(len(rows) + i, "bigru", 1, 1, d, hidden, 1, 1) for i, d in enumerate([inputs, 2 * hidden, 2 * hidden])]
    return [*rows, (len(rows), "dense", 1, 1, 2 * hidden, symbols, 1, 1)]


def config_fullconv(filters: tuple[int, ...] = (4, 4, 8, 8, 8), inputs: int = 512, width: int = 512, symbols: int = 42) -> list[tuple]:
    rows = conv_rows(list(filters))
    rows += [(len(rows) + i, "dilated", 3, 1, inputs if i == 0 else width, width, 1, 2**i) for i in range(6)]
    return [*rows, (len(rows), "dense", 1, 1, width, symbols, 1, 1)]


CONFIG = "layer int, kind string, k_t int, k_s int, c_in int, c_out int, stride int, dilation int"
PARAMS = """CASE kind WHEN 'conv3d' THEN k_t * k_s * k_s * c_in * c_out + c_out WHEN 'dilated' THEN k_t * c_in * c_out + c_out WHEN 'dense' THEN c_in * c_out + c_out
    WHEN 'bilstm' THEN 8 * (c_in * c_out + c_out * c_out + c_out) WHEN 'bigru' THEN 6 * (c_in * c_out + c_out * c_out + c_out) END"""


def param_count(config: DataFrame) -> DataFrame:
    return config.select("layer", "kind", F.expr(PARAMS).cast("long").alias("value"))


# ---- layers: each returns (output, backward); backward(gradient) -> (input gradient, parameter gradients)


def conv3d(x: np.ndarray, w: np.ndarray, b: np.ndarray, stride: int = 1, pad_t: bool = True) -> tuple[np.ndarray, Callable]:
    """x (T, H, W, C), w (kt, ks, ks, C, O): no spatial padding, temporal padding kept, unit temporal stride."""
    kt, ks = w.shape[:2]
    before = (kt - 1) // 2 if pad_t else 0
    after = kt - 1 - before if pad_t else 0
    padded = np.pad(x, ((before, after), (0, 0), (0, 0), (0, 0)))
    view = np.lib.stride_tricks.sliding_window_view(padded, (kt, ks, ks), axis=(0, 1, 2))[:, ::stride, ::stride]
    y = np.einsum("thwcabd,abdco->thwo", view, w, optimize=True) + b

    def back(g: np.ndarray) -> tuple[np.ndarray, Params]:
        dw = np.einsum("thwcabd,thwo->abdco", view, g, optimize=True)
        dx = np.zeros_like(padded)
        for a in range(kt):
            for i in range(ks):
                for j in range(ks):
                    dx[a : a + g.shape[0], i : i + stride * g.shape[1] : stride, j : j + stride * g.shape[2] : stride] += g @ w[a, i, j].T
        return dx[before : before + len(x)], {"w": dw, "b": g.sum(axis=(0, 1, 2))}

    return y, back


def conv3d_windows(x: np.ndarray, w: np.ndarray, b: np.ndarray, inner: bool = True) -> tuple[np.ndarray, Callable]:
    """``conv3d`` of many windows at once, x (n, T, H, W, C). Not ``inner``: the way back ends here."""
    kt, ks = w.shape[:2]
    before = (kt - 1) // 2
    padded = np.pad(x, ((0, 0), (before, kt - 1 - before), (0, 0), (0, 0), (0, 0)))
    view = np.lib.stride_tricks.sliding_window_view(padded, (kt, ks, ks), axis=(1, 2, 3))
    n, t, h, v = view.shape[:4]
    seen = view.transpose(0, 1, 2, 3, 5, 6, 7, 4).reshape(n * t * h * v, -1)
    y = (seen @ w.reshape(-1, w.shape[-1]) + b).reshape(n, t, h, v, -1)

    def back(g: np.ndarray) -> tuple[np.ndarray | None, Params]:
        flat, dx = g.reshape(len(seen), -1), None
        if inner:
            dx = np.zeros_like(padded)
            for a in range(kt):
                for i in range(ks):
                    for j in range(ks):
                        dx[:, a : a + t, i : i + h, j : j + v] += g @ w[a, i, j].T
            dx = dx[:, before : before + t]
        return dx, {"w": (seen.T @ flat).reshape(w.shape), "b": flat.sum(axis=0)}

    return y, back


def group_norm(x: np.ndarray, groups: int, gamma: np.ndarray, beta: np.ndarray, eps: float = 1e-5) -> tuple[np.ndarray, Callable]:
    """Statistics by channel group within the example: batch size does not matter."""
    c = x.shape[-1]
    flat = x.reshape(-1, groups, c // groups)
    mean, var = flat.mean(axis=(0, 2), keepdims=True), flat.var(axis=(0, 2), keepdims=True)
    hat = ((flat - mean) / np.sqrt(var + eps)).reshape(x.shape)

    def back(g: np.ndarray) -> tuple[np.ndarray, Params]:
        axes = tuple(range(g.ndim - 1))
        dh = (g * gamma).reshape(flat.shape)
        h = hat.reshape(flat.shape)
        dx = (dh - dh.mean(axis=(0, 2), keepdims=True) - h * (dh * h).mean(axis=(0, 2), keepdims=True)) / np.sqrt(var + eps)
        return dx.reshape(x.shape), {"gamma": (g * hat).sum(axis=axes), "beta": g.sum(axis=axes)}

    return hat * gamma + beta, back


def relu(x: np.ndarray) -> tuple[np.ndarray, Callable]:
    return np.maximum(x, 0), lambda g: (g * (x > 0), {})


def guided_relu(x: np.ndarray) -> tuple[np.ndarray, Callable]:
    """Its backward pass lets only positive gradients of active units through."""
    return np.maximum(x, 0), lambda g: (np.maximum(g, 0) * (x > 0), {})


def dense(x: np.ndarray, w: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, Callable]:
    return x @ w + b, lambda g: (g @ w.T, {"w": x.T @ g, "b": g.sum(axis=0)})


def _sig(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def lstm(x: np.ndarray, wx: np.ndarray, wh: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, Callable]:
    """One direction; gates in, forget, cell, out side by side."""
    n, h = len(x), wh.shape[0]
    hs, cs, gates = np.zeros((n + 1, h)), np.zeros((n + 1, h)), np.zeros((n, 4 * h))
    pre = x @ wx + b
    for t in range(n):
        z = pre[t] + hs[t] @ wh
        i, f, g, o = _sig(z[:h]), _sig(z[h : 2 * h]), np.tanh(z[2 * h : 3 * h]), _sig(z[3 * h :])
        cs[t + 1] = f * cs[t] + i * g
        hs[t + 1] = o * np.tanh(cs[t + 1])
        gates[t] = np.concatenate([i, f, g, o])

    def back(grad: np.ndarray) -> tuple[np.ndarray, Params]:
        dz, dh, dc = np.zeros_like(gates), np.zeros(h), np.zeros(h)
        for t in range(n - 1, -1, -1):
            i, f, g, o = np.split(gates[t], 4)
            dh = dh + grad[t]
            tc = np.tanh(cs[t + 1])
            dc = dc + dh * o * (1 - tc**2)
            dz[t] = np.concatenate([dc * g * i * (1 - i), dc * cs[t] * f * (1 - f), dc * i * (1 - g**2), dh * tc * o * (1 - o)])
            dh, dc = dz[t] @ wh.T, dc * f
        return dz @ wx.T, {"wx": x.T @ dz, "wh": hs[:-1].T @ dz, "b": dz.sum(axis=0)}

    return hs[1:], back


def gru(x: np.ndarray, wx: np.ndarray, wh: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, Callable]:
    """One direction; gates update, reset, candidate side by side."""
    n, h = len(x), wh.shape[0]
    hs, keep = np.zeros((n + 1, h)), np.zeros((n, 3 * h))
    pre = x @ wx + b
    for t in range(n):
        a = hs[t] @ wh[:, : 2 * h]
        u, r = _sig(pre[t, :h] + a[:h]), _sig(pre[t, h : 2 * h] + a[h:])
        c = np.tanh(pre[t, 2 * h :] + (r * hs[t]) @ wh[:, 2 * h :])
        hs[t + 1] = u * hs[t] + (1 - u) * c
        keep[t] = np.concatenate([u, r, c])

    def back(grad: np.ndarray) -> tuple[np.ndarray, Params]:
        dz, dwh, dh = np.zeros_like(keep), np.zeros_like(wh), np.zeros(h)
        for t in range(n - 1, -1, -1):
            u, r, c = np.split(keep[t], 3)
            dh = dh + grad[t]
            dc = dh * (1 - u) * (1 - c**2)
            drh = dc @ wh[:, 2 * h :].T
            du, dr = dh * (hs[t] - c) * u * (1 - u), drh * hs[t] * r * (1 - r)
            dz[t] = np.concatenate([du, dr, dc])
            dwh[:, : 2 * h] += np.outer(hs[t], dz[t, : 2 * h])
            dwh[:, 2 * h :] += np.outer(r * hs[t], dc)
            dh = dh * u + drh * r + dz[t, : 2 * h] @ wh[:, : 2 * h].T
        return dz @ wx.T, {"wx": x.T @ dz, "wh": dwh, "b": dz.sum(axis=0)}

    return hs[1:], back


def both_ways(cell: Callable, x: np.ndarray, fore: Params, rear: Params) -> tuple[np.ndarray, Callable]:
    a, back_a = cell(x, **fore)
    b, back_b = cell(x[::-1], **rear)

    def back(g: np.ndarray) -> tuple[np.ndarray, Params]:
        h = a.shape[1]
        da, pa_ = back_a(g[:, :h])
        db, pb = back_b(g[::-1, h:])
        return da + db[::-1], {**{f"f_{k}": v for k, v in pa_.items()}, **{f"r_{k}": v for k, v in pb.items()}}

    return np.concatenate([a, b[::-1]], axis=1), back


def dilated(x: np.ndarray, w: np.ndarray, b: np.ndarray, dilation: int) -> tuple[np.ndarray, Callable]:
    """x (T, D), w (k, D, O), same length out."""
    k = len(w)
    pad = dilation * (k - 1) // 2
    padded = np.pad(x, ((pad, dilation * (k - 1) - pad), (0, 0)))
    cut = [padded[i * dilation : i * dilation + len(x)] for i in range(k)]

    def back(g: np.ndarray) -> tuple[np.ndarray, Params]:
        dx = np.zeros_like(padded)
        for i in range(k):
            dx[i * dilation : i * dilation + len(x)] += g @ w[i].T
        return dx[pad : pad + len(x)], {"w": np.stack([c.T @ g for c in cut]), "b": g.sum(axis=0)}

    return sum(c @ w[i] for i, c in enumerate(cut)) + b, back


def dilated_windows(x: np.ndarray, w: np.ndarray, b: np.ndarray, inner: bool = True) -> tuple[np.ndarray, Callable]:
    """``dilated`` by 1 of many windows at once, x (n, T, D)."""
    y, back_3d = conv3d_windows(x[:, :, None, None], w[:, None, None], b, inner)

    def back(g: np.ndarray) -> tuple[np.ndarray | None, Params]:
        dx, grads = back_3d(g[:, :, None, None])
        return None if dx is None else dx[:, :, 0, 0], {"w": grads["w"][:, 0, 0], "b": grads["b"]}

    return y[:, :, 0, 0], back


def dropout(x: np.ndarray, rate: float, rng: np.random.Generator | None) -> tuple[np.ndarray, Callable]:
    if rng is None or not rate:
        return x, lambda g: (g, {})
    mask = (rng.random(x.shape) >= rate) / (1 - rate)
    return x * mask, lambda g: (g * mask, {})


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def batch_norm_statistics(df: DataFrame, key: str, value: str, worker: str | None = None) -> DataFrame:
    """Mean and variance by channel, over all rows or by worker: the exchange that group normalisation spares."""
    return df.groupBy(*([worker] if worker else []), key).agg(F.avg(value).alias("mean"), F.var_pop(value).alias("var"))


# ---- a model


@dataclass
class Net:
    """Vision module, temporal module and output layer. ``temporal``: lstm, gru or dilated."""

    temporal: str = "lstm"
    norm: bool = True
    drop: float = 0.0
    groups: int = 2
    dilations: tuple[int, ...] = (1, 2)
    stride: int = 1
    params: Params = field(default_factory=dict)
    activation: Callable = relu

    @staticmethod
    def start(size: int, channels: int, filters: list[int], hidden: int, layers: int, symbols: int, temporal: str = "lstm", seed: int = 0, k_t: int = 3, dilations: tuple[int, ...] = (1, 2), front: tuple[int, ...] = (), **more) -> Net:
        """``front``: widths of convolutions over three frames before the temporal module, as for spectrograms."""
        rng, p, c, s = np.random.default_rng(seed), {}, channels, size
        for i, o in enumerate(filters):
            p[f"conv{i}.w"] = rng.normal(0, (2 / (k_t * 9 * c)) ** 0.5, (k_t, 3, 3, c, o))
            p[f"conv{i}.b"], p[f"conv{i}.gamma"], p[f"conv{i}.beta"] = np.zeros(o), np.ones(o), np.zeros(o)
            c, s = o, s - 2
        d = c * s * s
        for i, o in enumerate(front):
            p[f"front{i}.w"], p[f"front{i}.b"], d = rng.normal(0, (2 / (3 * d)) ** 0.5, (3, d, o)), np.zeros(o), o
        for i in range(layers if temporal != "dilated" else len(dilations)):
            if temporal == "dilated":
                p[f"time{i}.w"], p[f"time{i}.b"] = rng.normal(0, (2 / (3 * d)) ** 0.5, (3, d, hidden)), np.zeros(hidden)
                d = hidden
            else:
                n = 4 if temporal == "lstm" else 3
                for way in "fr":
                    p[f"time{i}.{way}_wx"], p[f"time{i}.{way}_wh"], p[f"time{i}.{way}_b"] = rng.normal(0, d**-0.5, (d, n * hidden)), rng.normal(0, hidden**-0.5, (hidden, n * hidden)), np.zeros(n * hidden)
                d = 2 * hidden
            p[f"time{i}.gamma"], p[f"time{i}.beta"] = np.ones(d), np.zeros(d)
        p["out.w"], p["out.b"] = rng.normal(0, d**-0.5, (d, symbols)), np.zeros(symbols)
        return Net(temporal=temporal, params=p, dilations=dilations, **more)

    def forward(self, x: np.ndarray, rng: np.random.Generator | None = None, encode: bool = False) -> tuple[np.ndarray, Callable]:
        """x (T, H, W, C) -> logits (T, symbols), and the way back to (input gradient, parameter gradients).

        With ``encode`` the temporal module's output is what comes back: the frames that a decoder attends to.
        """
        steps: list[tuple[str, Callable]] = []
        p = self.params

        def do(name: str, result: tuple[np.ndarray, Callable]) -> np.ndarray:
            steps.append((name, result[1]))
            return result[0]

        i = 0
        while f"conv{i}.w" in p:
            x = do(f"conv{i}.", conv3d(x, p[f"conv{i}.w"], p[f"conv{i}.b"], self.stride))
            if self.norm:
                x = do(f"conv{i}.", group_norm(x, self.groups, p[f"conv{i}.gamma"], p[f"conv{i}.beta"]))
            x = do("", self.activation(x))
            i += 1
        shape = x.shape
        x = do("", (x.reshape(shape[0], -1), lambda g: (g.reshape(shape), {})))
        i = 0
        while f"front{i}.w" in p:
            x = do(f"front{i}.", dilated(x, p[f"front{i}.w"], p[f"front{i}.b"], 1))
            x = do("", self.activation(x))
            i += 1
        i = 0
        while f"time{i}.gamma" in p:
            if self.temporal == "dilated":
                x = do(f"time{i}.", dilated(x, p[f"time{i}.w"], p[f"time{i}.b"], self.dilations[i]))
                x = do("", self.activation(x))
            else:
                ways = [{k: p[f"time{i}.{w}_{k}"] for k in ("wx", "wh", "b")} for w in "fr"]
                x = do(f"time{i}.", both_ways(lstm if self.temporal == "lstm" else gru, x, *ways))
            if self.norm:
                x = do(f"time{i}.", group_norm(x, self.groups, p[f"time{i}.gamma"], p[f"time{i}.beta"]))
            x = do("", dropout(x, self.drop, rng))
            i += 1
        if not encode:
            x = do("out.", dense(x, p["out.w"], p["out.b"]))

        def back(g: np.ndarray) -> tuple[np.ndarray, Params]:
            grads: Params = {}
            for name, step in reversed(steps):
                g, own = step(g)
                grads.update({name + k: v for k, v in own.items()})
            return g, grads

        return x, back

    def loss(self, x: np.ndarray, label: list[int], rng: np.random.Generator | None = None) -> tuple[float, Params]:
        logits, back = self.forward(x, rng)
        value, g = ctc.loss_and_gradient(logits, label)
        return (value, back(g)[1]) if np.isfinite(value) else (0.0, {})

    def saliency(self, x: np.ndarray, label: list[int]) -> np.ndarray:
        """Gradient of the label's log likelihood by the input, guided."""
        plain, self.activation = self.activation, guided_relu
        try:
            logits, back = self.forward(x)
            return -back(ctc.loss_and_gradient(logits, label)[1])[0]
        finally:
            self.activation = plain


def _clip(row, size: int, channels: int) -> np.ndarray:
    return np.frombuffer(row.px, np.float32).reshape(-1, size, size, channels).astype(float)


GRADIENT_BLOCK = 1 << 18  # numbers of a gradient in one row


def train(clips: DataFrame, net: Net, size: int, channels: int = 1, steps: int = 20, rate: float = 0.05, workers: int = 4, per_worker: int = 2, seed: int = 0) -> tuple[Net, list[float]]:
    """Synchronous data-parallel steps. clips (clip_id, px: float32 frames, label: array of symbols).

    Rows are dealt to the workers once, with a place in each worker's turn; a step reads the rows whose turn it is. A
    worker's gradient leaves it in blocks, blocks of one place are summed in parallel, and the driver gets one gradient,
    of the model's size, however many workers there are.
    """
    sc = clips.sparkSession.sparkContext
    turn = Window.partitionBy("worker")
    dealt = clips.select("clip_id", "px", "label", F.pmod(F.xxhash64("clip_id"), F.lit(workers)).cast("int").alias("worker"))
    dealt = written(dealt.withColumn("place", F.row_number().over(turn.orderBy("clip_id")) - 1).withColumn("n", F.count(F.lit(1)).over(turn)), "dealt")
    names = sorted(net.params)
    moment: Params = {}
    losses = []
    for step in range(steps):
        cast = sc.broadcast(net)

        def part(batches: Iterator[pd.DataFrame], cast=cast, step=step) -> Iterator[pd.DataFrame]:
            total, loss, n = {}, 0.0, 0
            for b in batches:
                for r in b.itertuples(index=False):
                    value, grads = cast.value.loss(_clip(r, size, channels), [int(i) for i in r.label], np.random.default_rng([seed, step, int(r.clip_id)]))
                    loss, n = loss + value, n + 1
                    for k, g in grads.items():
                        total[k] = total.get(k, 0) + g
            if n:
                flat = np.concatenate([np.ravel(total.get(k, np.zeros_like(cast.value.params[k]))) for k in names])
                for i in range(0, len(flat), GRADIENT_BLOCK):
                    yield pd.DataFrame({"block": [i // GRADIENT_BLOCK], "loss": [loss if i == 0 else 0.0], "n": [n], "g": [flat[i : i + GRADIENT_BLOCK].tobytes()]})

        def add(rows: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"block": rows["block"][:1], "loss": [rows["loss"].sum()], "n": [rows["n"].sum()], "g": [sum(np.frombuffer(g) for g in rows["g"]).tobytes()]})

        now = dealt.where(F.pmod(F.col("place") - F.lit(step * per_worker), F.col("n")) < per_worker).select("clip_id", "px", "label")
        kind = "block int, loss double, n long, g binary"
        found = sorted(now.mapInPandas(part, kind).groupBy("block").applyInPandas(add, kind).collect(), key=lambda r: r.block)  # one gradient
        if not found:
            break
        n, flat, at = found[0].n, np.concatenate([np.frombuffer(r.g) for r in found]) / found[0].n, 0
        norm = max(1.0, float(np.linalg.norm(flat)) / 5)
        fresh = {}
        for k in names:
            shape = net.params[k].shape
            g = flat[at : at + net.params[k].size].reshape(shape) / norm
            at += net.params[k].size
            moment[k] = 0.9 * moment.get(k, 0) + g
            fresh[k] = net.params[k] - rate * moment[k]
        net = Net(net.temporal, net.norm, net.drop, net.groups, net.dilations, net.stride, fresh)
        losses.append(found[0].loss / n)
        cast.unpersist()
    return net, losses


def saliency(clips: DataFrame, net: Net, size: int, channels: int = 1) -> DataFrame:
    """clips (clip_id, px, label) -> clip_id, t, strength (of the guided gradient), map (its pixels), entropy, top (three symbols).

    One row a frame, no shuffle.
    """
    cast = clips.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for r in b.itertuples(index=False):
                x = _clip(r, size, channels)
                g, p = cast.value.saliency(x, [int(i) for i in r.label]), softmax(cast.value.forward(x)[0])
                for t in range(len(x)):
                    rows.append((r.clip_id, t, float(np.abs(g[t]).sum()), g[t].ravel().tolist(), float(-(p[t] * np.log(np.maximum(p[t], 1e-300))).sum()), np.argsort(-p[t], kind="stable")[:3].tolist()))
            yield pd.DataFrame(rows, columns=["clip_id", "t", "strength", "map", "entropy", "top"])

    return clips.select("clip_id", "px", "label").mapInPandas(run, "clip_id long, t int, strength double, map array<double>, entropy double, top array<int>")


def predict(clips: DataFrame, net: Net, size: int, channels: int = 1, key: str = "clip_id") -> DataFrame:
    """key, lattice (array of frames of probabilities). One pass, no shuffle."""
    cast = clips.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({key: b[key], "lattice": [softmax(cast.value.forward(_clip(r, size, channels))[0]).tolist() for r in b.itertuples(index=False)]})

    return clips.select(key, "px").mapInPandas(run, f"{key} {clips.schema[key].dataType.simpleString()}, lattice array<array<double>>")


def save_model(spark: SparkSession, net: Net, path: str) -> None:
    """Weights as rows (layer, name, shape, data) and one row for the settings."""
    rows = [(*k.split("."), list(v.shape), bytearray(v.astype(np.float64).tobytes())) for k, v in net.params.items()]
    settings = json.dumps({"temporal": net.temporal, "norm": net.norm, "drop": net.drop, "groups": net.groups, "dilations": net.dilations, "stride": net.stride})
    spark.createDataFrame([*rows, ("settings", settings, [], bytearray())], "layer string, name string, shape array<int>, data binary").coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> Net:
    rows = spark.read.parquet(path).collect()  # of the model's size
    settings = next(json.loads(r.name) for r in rows if r.layer == "settings")
    params = {f"{r.layer}.{r.name}": np.frombuffer(r.data).reshape(r["shape"]).copy() for r in rows if r.layer != "settings"}
    return Net(**{**settings, "dilations": tuple(settings["dilations"])}, params=params)


# ---- attention over characters


@dataclass
class AttnDecoder:
    """A recurrent decoder that attends to encoded frames, one character at a time. Symbols: 0 ends, the rest are letters."""

    params: Params

    @staticmethod
    def start(d: int, hidden: int, symbols: int, seed: int = 0) -> AttnDecoder:
        rng = np.random.default_rng(seed)
        n = lambda *s: rng.normal(0, s[0] ** -0.5, s)
        return AttnDecoder({"embed": n(symbols, hidden), "wx": n(hidden + d, 3 * hidden), "wh": n(hidden, 3 * hidden), "b": np.zeros(3 * hidden), "key": n(d, hidden), "out": n(hidden + d, symbols), "bias": np.zeros(symbols)})

    def step(self, state: np.ndarray, last: int, frames: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        p, h = self.params, len(self.params["wh"])
        a = softmax((frames @ p["key"]) @ state / h**0.5)
        context = a @ frames
        x = np.concatenate([p["embed"][last], context])
        pre, rec = x @ p["wx"] + p["b"], state @ p["wh"][:, : 2 * h]
        u, r = _sig(pre[:h] + rec[:h]), _sig(pre[h : 2 * h] + rec[h:])
        c = np.tanh(pre[2 * h :] + (r * state) @ p["wh"][:, 2 * h :])
        state = u * state + (1 - u) * c
        logits = np.concatenate([state, context]) @ p["out"] + p["bias"]
        return state, logits - np.logaddexp.reduce(logits)

    def score(self, frames: np.ndarray, label: list[int]) -> float:
        state, last, total = np.zeros(len(self.params["wh"])), 0, 0.0
        for k in [*label, 0]:
            state, lp = self.step(state, last, frames)
            total, last = total + lp[k], k
        return float(total)

    def loss(self, frames: np.ndarray, label: list[int]) -> tuple[float, Params, np.ndarray]:
        """-log p of the label given each symbol before, its gradients by the weights and by the frames."""
        p, h = self.params, len(self.params["wh"])
        keys, state, last, kept, value = frames @ p["key"], np.zeros(h), 0, [], 0.0
        for k in [*label, 0]:
            a = softmax(keys @ state / h**0.5)
            context = a @ frames
            x = np.concatenate([p["embed"][last], context])
            pre, rec = x @ p["wx"] + p["b"], state @ p["wh"][:, : 2 * h]
            u, r = _sig(pre[:h] + rec[:h]), _sig(pre[h : 2 * h] + rec[h:])
            c = np.tanh(pre[2 * h :] + (r * state) @ p["wh"][:, 2 * h :])
            new = u * state + (1 - u) * c
            q = softmax(np.concatenate([new, context]) @ p["out"] + p["bias"])
            value -= float(np.log(max(q[k], 1e-300)))
            kept.append((state, last, a, context, x, u, r, c, new, q, k))
            state, last = new, k
        g = {n: np.zeros_like(v) for n, v in p.items()}
        d_frames, d_keys, d_state = np.zeros_like(frames), np.zeros_like(keys), np.zeros(h)
        for state, last, a, context, x, u, r, c, new, q, k in reversed(kept):
            d = q.copy()
            d[k] -= 1
            g["out"] += np.outer(np.concatenate([new, context]), d)
            g["bias"] += d
            both = p["out"] @ d
            d_new, d_context = both[:h] + d_state, both[h:]
            d_c = d_new * (1 - u) * (1 - c**2)
            d_rh = p["wh"][:, 2 * h :] @ d_c
            d_u, d_r = d_new * (state - c) * u * (1 - u), d_rh * state * r * (1 - r)
            d_pre = np.concatenate([d_u, d_r, d_c])
            g["wx"] += np.outer(x, d_pre)
            g["b"] += d_pre
            g["wh"][:, : 2 * h] += np.outer(state, d_pre[: 2 * h])
            g["wh"][:, 2 * h :] += np.outer(r * state, d_c)
            d_x = p["wx"] @ d_pre
            g["embed"][last] += d_x[:h]
            d_context = d_context + d_x[h:]
            d_a = frames @ d_context
            d_frames += np.outer(a, d_context)
            d_e = a * (d_a - a @ d_a) / h**0.5
            d_keys += np.outer(d_e, state)
            d_state = d_new * u + d_rh * r + p["wh"][:, : 2 * h] @ d_pre[: 2 * h] + keys.T @ d_e
        g["key"] = frames.T @ d_keys
        return value, g, d_frames + d_keys @ p["key"].T

    def beam(self, frames: np.ndarray, width: int = 4, most: int = 30) -> list[tuple[list[int], float]]:
        live, done = [((), 0.0, np.zeros(len(self.params["wh"])))], []
        for _ in range(most):
            ahead = []
            for seq, s, state in live:
                new, lp = self.step(state, seq[-1] if seq else 0, frames)
                ahead += [(s + lp[k], seq, k, new) for k in np.argsort(-lp)[: width + 1]]
            ahead.sort(key=lambda x: -x[0])
            live = []
            for s, seq, k, new in ahead[:width]:
                done.append((list(seq), float(s))) if k == 0 else live.append(((*seq, int(k)), s, new))
            if not live:
                break
        return sorted(done or [(list(seq), float(s)) for seq, s, _ in live], key=lambda x: -x[1])[:width]

    def fit(self, examples: list[tuple[np.ndarray, list[int]]], rounds: int = 100, rate: float = 0.05) -> list[float]:
        """Adaptive gradient steps over all examples; the mean loss of each."""
        seen, losses = {k: np.full_like(v, 1e-8) for k, v in self.params.items()}, []
        for _ in range(rounds):
            found = [self.loss(x, y) for x, y in examples]
            for k in self.params:
                g = sum(f[1][k] for f in found) / len(found)
                seen[k] += g * g
                self.params[k] = self.params[k] - rate * g / np.sqrt(seen[k])
            losses.append(float(np.mean([f[0] for f in found])))
        return losses
