"""Audio and video synchrony: pairs, distance, loss, window scores, measures, and two rounds of self-filtering."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipflow.operators import nn


def sync_distance(a: str, v: str) -> Column:
    return F.expr(f"sqrt(aggregate(zip_with({a}, {v}, (x, y) -> cast(x AS double) - cast(y AS double)), 0D, (s, d) -> s + d * d))")


def sync_classify(df: DataFrame, threshold: float, a: str = "a", v: str = "v") -> DataFrame:
    """In step if the embeddings are closer than the threshold."""
    return df.withColumn("d", sync_distance(a, v)).withColumn("pred", (F.col("d") < threshold).cast("int"))


def contrastive_loss(d: Column, y: Column, margin: float) -> Column:
    """Pairs in step are pulled together, others pushed apart up to the margin."""
    return F.when(y == 1, d * d).otherwise(F.pow(F.greatest(F.lit(0.0), margin - d), 2))


def equally_spaced(n: str, count: int, width: int) -> Column:
    """Starts of ``count`` windows of ``width`` over 0 .. n - 1, the first at 0 and the last at n - width."""
    return F.expr(f"transform(sequence(0, {count - 1}), i -> cast(floor(i * ({n} - {width}) / {count - 1}D) AS int))")


def window_scores(df: DataFrame, distances: str, count: int = 100, width: int = 9) -> DataFrame:
    """Mean over equally spaced windows of the windows' mean distance; null for clips shorter than a window.

    Each window reads its own distances, so a clip of any length costs the same ``count`` times ``width`` lookups.
    """
    out = df.withColumn("_n", F.size(distances))
    starts = F.when(F.col("_n") >= width, equally_spaced("_n", count, width))
    out = out.withColumn("_starts", starts)
    score = f"aggregate(_starts, 0D, (s, i) -> s + aggregate(slice({distances}, i + 1, {width}), 0D, (a, x) -> a + x) / {width}) / {count}"
    return out.withColumn("score", F.expr(score)).drop("_n", "_starts")


def make_pairs(df: DataFrame, group: str, order: str, shift: int) -> DataFrame:
    """df (group, order, a, v) -> y = 1 rows as they are and y = 0 rows whose video is ``shift`` rows away in the group."""
    from pyspark.sql import Window

    w = Window.partitionBy(group).orderBy(order)
    moved = df.withColumn("v", F.lead("v", shift).over(w)).where("v IS NOT NULL")
    return df.withColumn("y", F.lit(1)).unionByName(moved.withColumn("y", F.lit(0)))


def random_shifts(df: DataFrame, group: str, order: str, seed: str = "shift") -> DataFrame:
    """df (group, order, a, v) -> y = 1 rows as they are and y = 0 rows whose video is a random number of rows away in the group.

    The number is from 1 to the group's size less 1, by a hash of the row, and wraps around, so each row has one; groups of
    one row have none. Rows are numbered in their group once, and the shifted video is an equi-join on the number.
    """
    from pyspark.sql import Window

    from clipflow.sources.standin import hash8

    of = Window.partitionBy(group)
    rows = df.withColumn("_n", F.count(F.lit(1)).over(of)).withColumn("_i", F.row_number().over(of.orderBy(order)) - 1)
    step = 1 + hash8(F.lit(seed), F.col(order).cast("string")) % (F.col("_n") - 1)
    asked = rows.where("_n > 1").withColumn("_j", ((F.col("_i") + step) % F.col("_n")).cast("int")).drop("v")
    videos = rows.select(F.col(group).alias("_g"), F.col("_i").alias("_k"), "v")
    moved = asked.join(videos, (F.col(group) == F.col("_g")) & (F.col("_j") == F.col("_k")))
    names = df.columns
    return df.withColumn("y", F.lit(1)).unionByName(moved.select(*names).withColumn("y", F.lit(0)))


def accuracy(df: DataFrame, pred: str = "pred", truth: str = "y") -> DataFrame:
    """accuracy, precision, recall in one pass."""
    p, t = F.col(pred), F.col(truth)
    hit = F.count_if((p == 1) & (t == 1))
    return df.agg(F.avg((p == t).cast("double")).alias("accuracy"), (hit / F.count_if(p == 1)).alias("precision"), (hit / F.count_if(t == 1)).alias("recall"))


def log_mel(signal: np.ndarray, rate: float, n_fft: int = 64, hop: int = 16, bands: int = 8) -> np.ndarray:
    """Log energies in triangular bands equally spaced in mels."""
    window = np.hanning(n_fft)
    starts = range(0, max(len(signal) - n_fft, 0) + 1, hop)
    frames = np.stack([np.pad(signal[s : s + n_fft], (0, max(0, n_fft - len(signal[s : s + n_fft])))) * window for s in starts])
    power = np.abs(np.fft.rfft(frames, axis=1)) ** 2
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = 700 * (10 ** (np.linspace(0, mel(rate / 2), bands + 2) / 2595) - 1)
    freq = np.fft.rfftfreq(n_fft, 1 / rate)
    up = (freq[None] - edges[:-2, None]) / np.maximum(edges[1:-1] - edges[:-2], 1e-12)[:, None]
    down = (edges[2:, None] - freq[None]) / np.maximum(edges[2:] - edges[1:-1], 1e-12)[:, None]
    return np.log(power @ np.clip(np.minimum(up, down), 0, None).T + 1e-10)


@dataclass
class Towers:
    """Two linear towers into one space: ``mode='3d'`` sees all frames of a window, ``'2d'`` the mean of single frames."""

    audio: np.ndarray
    video: np.ndarray
    mode: str = "3d"

    @staticmethod
    def start(n_audio: int, frames: int, pixels: int, dim: int = 8, mode: str = "3d", seed: int = 0) -> Towers:
        rng = np.random.default_rng(seed)
        n_video = frames * pixels if mode == "3d" else pixels
        return Towers(rng.normal(0, n_audio**-0.5, (n_audio, dim)), rng.normal(0, n_video**-0.5, (n_video, dim)), mode)

    def embed(self, a: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """a (n, n_audio), v (n, frames, pixels)."""
        return a @ self.audio, self._view(v) @ self.video

    def _view(self, v: np.ndarray) -> np.ndarray:
        return v.reshape(len(v), -1) if self.mode == "3d" else v.mean(axis=1)

    def gradient(self, a: np.ndarray, v: np.ndarray, y: np.ndarray, margin: float) -> tuple[float, np.ndarray, np.ndarray]:
        """Summed contrastive loss and its gradients."""
        ea, ev = self.embed(a, v)
        diff = ea - ev
        d = np.sqrt((diff**2).sum(axis=1) + 1e-12)
        gap = np.maximum(0, margin - d)
        loss = np.where(y == 1, d**2, gap**2).sum()
        g = np.where(y == 1, 2.0, -2 * gap / d)[:, None] * diff
        return float(loss), a.T @ g, -self._view(v).T @ g


#: Windows that go through the networks as one array.
WINDOWS_AT_ONCE = 256


@dataclass
class ConvTowers:
    """Two networks into one space: spatiotemporal convolutions over a window of square frames, convolutions in time over
    its spectrogram. ``k_t`` 1 sees each frame for itself."""

    params: dict[str, np.ndarray]
    side: int
    bands: int

    @staticmethod
    def start(bands: int, frames: int, side: int, dim: int = 8, filters: tuple[int, ...] = (4, 4), width: int = 12, k_t: int = 3, seed: int = 0) -> ConvTowers:
        rng, p, c, s = np.random.default_rng(seed), {}, 1, side
        for i, o in enumerate(filters):
            p[f"v{i}.w"], p[f"v{i}.b"] = rng.normal(0, (2 / (k_t * 9 * c)) ** 0.5, (k_t, 3, 3, c, o)), np.zeros(o)
            c, s = o, s - 2
        d = frames * s * s * c
        p["v.w"], p["v.b"] = rng.normal(0, d**-0.5, (d, dim)), np.zeros(dim)
        p["a0.w"], p["a0.b"] = rng.normal(0, (2 / (3 * bands)) ** 0.5, (3, bands, width)), np.zeros(width)
        p["a.w"], p["a.b"] = rng.normal(0, (frames * width) ** -0.5, (frames * width, dim)), np.zeros(dim)
        return ConvTowers(p, side, bands)

    def _tower(self, name: str, x: np.ndarray) -> tuple[np.ndarray, Callable]:
        """Windows through one of the networks, and the way back to its parameters' summed gradients."""
        p, steps = self.params, []

        def do(label: str, result: tuple[np.ndarray, Callable]) -> np.ndarray:
            steps.append((label, result[1]))
            return result[0]

        i = 0
        while f"{name}{i}.w" in p:
            w, b = p[f"{name}{i}.w"], p[f"{name}{i}.b"]
            x = do(f"{name}{i}.", (nn.conv3d_windows if name == "v" else nn.dilated_windows)(x, w, b, i > 0))
            x = do("", nn.relu(x))
            i += 1
        shape = x.shape
        x = do("", (x.reshape(len(x), -1), lambda g: (g.reshape(shape), {})))
        x = do(f"{name}.", nn.dense(x, p[f"{name}.w"], p[f"{name}.b"]))

        def back(g: np.ndarray) -> dict[str, np.ndarray]:
            grads = {}
            for label, step in reversed(steps):
                g, own = step(g)
                grads |= {label + k: v for k, v in own.items()}
            return grads

        return x, back

    def _blocks(self, a: np.ndarray, v: np.ndarray) -> Iterator[tuple]:
        """Both networks over blocks of windows: (their rows, audio's embeddings and way back, video's)."""
        frames = v.shape[1]
        for at in range(0, len(a), WINDOWS_AT_ONCE):
            rows = slice(at, at + WINDOWS_AT_ONCE)
            yield rows, self._tower("a", a[rows].reshape(-1, frames, self.bands)), self._tower("v", v[rows].reshape(-1, frames, self.side, self.side, 1))

    def embed(self, a: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """a (n, frames * bands), v (n, frames, side * side)."""
        both = [(ea, ev) for _, (ea, _), (ev, _) in self._blocks(a, v)]
        return np.concatenate([x for x, _ in both]), np.concatenate([x for _, x in both])

    def step(self, a: np.ndarray, v: np.ndarray, y: np.ndarray, margin: float) -> tuple[float, dict[str, np.ndarray]]:
        """Summed contrastive loss and its gradients."""
        total, loss = {k: np.zeros_like(x) for k, x in self.params.items()}, 0.0
        for rows, (ea, back_a), (ev, back_v) in self._blocks(a, v):
            diff, same = ea - ev, y[rows] == 1
            d = np.sqrt((diff**2).sum(axis=1) + 1e-12)
            gap = np.maximum(0.0, margin - d)
            loss += float(np.where(same, d * d, gap * gap).sum())
            g = np.where(same, 2.0, -2 * gap / d)[:, None] * diff
            for grads in (back_a(g), back_v(-g)):
                for k, x in grads.items():
                    total[k] += x
        return loss, total


def _pairs_of(b: pa.RecordBatch, frames: int) -> tuple[np.ndarray, np.ndarray]:
    """Columns a and v of a batch as arrays."""
    wide = lambda name: b.column(b.schema.get_field_index(name)).flatten().to_numpy(zero_copy_only=False)
    return wide("a").reshape(b.num_rows, -1), wide("v").reshape(b.num_rows, frames, -1)


def train_towers(pairs: DataFrame, towers: Towers | ConvTowers, frames: int, epochs: int = 30, rate: float = 0.5, margin: float = 1.0, longest: float | None = None, gate: tuple[Towers | ConvTowers, float] | None = None) -> tuple[Towers | ConvTowers, list[float]]:
    """Synchronous data-parallel steps: tasks sum gradients over their rows, those sums meet by parameter, and the driver
    gets one gradient of the model's size. A gradient longer than ``longest`` is cut to that length. With ``gate``, positive
    pairs that are further apart by its towers than its distance are left out, in the tasks that read them."""
    sc = pairs.sparkSession.sparkContext
    losses = []
    for _ in range(epochs):
        cast = sc.broadcast((towers, gate))

        def part(batches: Iterator[pa.RecordBatch], cast=cast) -> Iterator[pa.RecordBatch]:
            (t, gate), total, loss, n = cast.value, None, 0.0, 0
            for b in batches:
                if b.num_rows:
                    (a, v), y = _pairs_of(b, frames), b.column(2).to_numpy()
                    if gate is not None:
                        near = (y == 0) | (_apart(gate[0], a, v) <= gate[1])
                        a, v, y = a[near], v[near], y[near]
                    if not len(y):
                        continue
                    if isinstance(t, ConvTowers):
                        value, grads = t.step(a, v, y, margin)
                    else:
                        value, ga, gv = t.gradient(a, v, y, margin)
                        grads = {"audio": ga, "video": gv}
                    total = grads if total is None else {k: total[k] + g for k, g in grads.items()}
                    loss, n = loss + value, n + len(y)
            if total is not None:
                yield pa.RecordBatch.from_pydict({"name": list(total), "loss": [float(loss)] * len(total), "n": [n] * len(total), "g": [g.astype(float).tobytes() for g in total.values()]})

        def add(rows: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"name": rows["name"][:1], "loss": [rows["loss"].sum()], "n": [rows["n"].sum()], "g": [sum(np.frombuffer(g) for g in rows["g"]).tobytes()]})

        kind = "name string, loss double, n long, g binary"
        rows = pairs.select("a", "v", "y").mapInArrow(part, kind).groupBy("name").applyInPandas(add, kind).collect()  # a row a parameter
        if not rows:
            break
        moved = {r["name"]: rate * np.frombuffer(r["g"]) / r["n"] for r in rows}
        length = float(np.sqrt(sum((g**2).sum() for g in moved.values()))) / rate
        if longest is not None and length > longest:
            moved = {k: g * (longest / length) for k, g in moved.items()}
        if isinstance(towers, ConvTowers):
            towers = ConvTowers({k: p - moved[k].reshape(p.shape) for k, p in towers.params.items()}, towers.side, towers.bands)
        else:
            towers = Towers(towers.audio - moved["audio"].reshape(towers.audio.shape), towers.video - moved["video"].reshape(towers.video.shape), towers.mode)
        losses.append(rows[0]["loss"] / rows[0]["n"])
        cast.unpersist()
    return towers, losses


def _apart(towers: Towers | ConvTowers, a: np.ndarray, v: np.ndarray) -> np.ndarray:
    ea, ev = towers.embed(a, v)
    return np.sqrt(((ea - ev) ** 2).sum(axis=1))


def embed(pairs: DataFrame, towers: Towers | ConvTowers, frames: int, inputs: bool = True) -> DataFrame:
    """pairs with d, the distance of the two embeddings; without ``inputs``, their other columns only."""
    cast = pairs.sparkSession.sparkContext.broadcast(towers)
    kept = [f for f in pairs.schema if inputs or f.name not in ("a", "v")]

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            d = _apart(cast.value, *_pairs_of(b, frames)) if b.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*[b.column(b.schema.get_field_index(f.name)) for f in kept], pa.array(d, pa.float64())], names=[*[f.name for f in kept], "d"])

    return pairs.mapInArrow(part, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in kept) + ", d double")


def distances(pairs: DataFrame, towers: Towers | ConvTowers, frames: int) -> DataFrame:
    """``embed`` without the towers' inputs."""
    return embed(pairs, towers, frames, inputs=False)


def self_filter(pairs: DataFrame, towers: Towers | ConvTowers, frames: int, keep: float = 0.8, rounds: int = 2, epochs: int = 20, rate: float = 0.5, longest: float | None = None) -> tuple[Towers | ConvTowers, DataFrame, list[float]]:
    """Train on all, keep the positive pairs with the smallest distances, fine-tune on those, filter again.

    The threshold of a round is a quantile of the positives' distances; negatives stay as they are.
    """
    kept, losses, gate = pairs, [], None
    for _ in range(rounds):
        towers, seen = train_towers(pairs, towers, frames, epochs, rate, longest=longest, gate=gate)
        losses += seen
        cut = distances(pairs.select("a", "v", "y"), towers, frames).where("y = 1").agg(F.percentile_approx("d", keep)).first()[0]
        gate = towers, cut if cut is not None else 0.0
    if gate is not None:
        kept = embed(pairs, gate[0], frames).where((F.col("y") == 0) | (F.col("d") <= gate[1])).drop("d")
    return towers, kept, losses
