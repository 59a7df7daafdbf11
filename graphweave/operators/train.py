"""Full-batch training over a vertex-cut: replicated weights, partitioned graph, gradients summed per epoch.

Every clone computes its own activations from its partition and what synchronisation gives it; the loss is taken
at root clones. Backward is the exact transpose: gradients of the synchronised sums are synchronised in the same
mode, then summed along reversed local edges. In sync_full that equals training on the whole graph.

Only weights, one gradient row a partition, and measures reach the driver; tables are checkpointed each step.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphweave.operators import remote
from graphweave.session import prepare
from graphweave.storage import checkpointed, checkpointed_as_dealt


@dataclass
class Model:
    """Weights and biases by layer."""

    layers: list[tuple[np.ndarray, np.ndarray]]

    @staticmethod
    def fresh(dims: list[int], seed: int = 0) -> Model:
        rng = np.random.default_rng(seed)
        return Model([(rng.uniform(-1, 1, (a, b)) * np.sqrt(6 / (a + b)), np.zeros(b)) for a, b in zip(dims, dims[1:])])


#: The two configurations of the experiments, but for input width and classes.
SMALL_HIDDEN, LARGE_HIDDEN = [16], [256, 256]
#: Above so many columns Spark gives up generated code.
WIDEST_COLUMNS = 100
#: Partitions of at most so many directed edges (64 MB of ids) are summed as arrays, which need no sort by vertex.
MOST_ARRAY_EDGES = 4_000_000


@dataclass
class Optimiser:
    """Gradient descent or Adam, with L2 decay of the weights."""

    kind: str = "adam"
    lr: float = 0.01
    decay: float = 5e-4
    steps: int = 0
    state: dict = field(default_factory=dict)

    def update(self, model: Model, grads: list[tuple[np.ndarray, np.ndarray]]) -> None:
        self.steps += 1
        for i, ((w, b), (dw, db)) in enumerate(zip(model.layers, grads)):
            model.layers[i] = (w - self._step((i, "w"), dw + self.decay * w), b - self._step((i, "b"), db))

    def _step(self, key, grad: np.ndarray) -> np.ndarray:
        if self.kind == "sgd":
            return self.lr * grad
        m, v = self.state.get(key, (0.0, 0.0))
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        self.state[key] = (m, v)
        return self.lr * (m / (1 - 0.9**self.steps)) / (np.sqrt(v / (1 - 0.999**self.steps)) + 1e-8)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def _matrix(column) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(column), -1)


def _lists(x: np.ndarray):
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.reshape(-1)))


class Trainer:
    def __init__(self, cut: DataFrame, roles: DataFrame, features: DataFrame, labels: DataFrame, dims: list[int], mode: str = "sync_full", delay: int = 5, bins: int | None = None, norm_plus: int = 1, optimiser: Optimiser | None = None, seed: int = 0, overlap: bool = False):
        """cut (src, dst, part); roles as from layout.with_roles; features (vid, feat); labels (vid, y, split).

        Edges and clones are dealt by part once; after that only split vertices' vectors move between partitions.
        """
        prepare(cut.sparkSession)
        self.parts = (cut.agg(F.max("part")).first()[0] or 0) + 1
        self.cut = remote.dealt(cut.select("src", "dst", "part"), self.parts)
        self.largest = self.cut.groupBy("part").count().agg(F.max("count")).first()[0] or 0
        degree_keys = ["part", "dst"] if mode == "local_only" else ["dst"]
        degree = self.cut.groupBy(*degree_keys).agg(F.count("*").alias("degree")).withColumnRenamed("dst", "vid")
        rows = roles.join(degree, [c for c in ("vid", "part") if c in degree.columns], "left")
        base = rows.select("vid", "part", "root_part", "is_root", "is_split", "bin", F.greatest(F.coalesce("degree", F.lit(0)) + norm_plus, F.lit(1)).cast("double").alias("norm"))
        self.roles = remote.dealt(base.join(labels, "vid", "left").withColumn("split", F.when(F.col("is_root"), F.col("split"))), self.parts)
        self.h0 = remote.dealt(self.roles.select("vid", "part").join(features, "vid"), self.parts)
        self.n_train = self.roles.where("split = 'train'").count()
        self.dims, self.mode, self.delay, self.bins = dims, mode, delay, bins
        self.model, self.optimiser = Model.fresh(dims, seed), optimiser or Optimiser()
        self.delayed = {}
        self.epoch, self.history, self.overlap = 0, [], overlap
        self.seconds = {"local": 0.0, "remote": 0.0}

    def _timed(self, stage: str, df: DataFrame) -> DataFrame:
        began = time.monotonic()
        df = checkpointed_as_dealt(df) if stage == "local" else checkpointed(df)
        self.seconds[stage] += time.monotonic() - began
        return df

    def _local(self, features: DataFrame, width: int, direction: str = "forward") -> DataFrame:
        """Sums inside partitions: as arrays of a partition where its edges are few or vectors too wide for generated code, else as columns."""
        kernel = "csr" if width > WIDEST_COLUMNS or self.largest <= MOST_ARRAY_EDGES else "columns"
        return self._timed("local", remote.local_aggregate(self.cut, features, width, direction=direction, kernel=kernel))

    def _sync(self, partials: DataFrame, width: int, where: str) -> DataFrame:
        full = remote.complete(partials, self.roles, width)
        if self.mode != "delayed":
            return self._timed("remote", remote.sync(full, width, self.mode))
        if where not in self.delayed:
            self.delayed[where] = remote.DelayedSync(width, self.delay, self.bins, overlap=self.overlap)
        full = self._timed("remote", full)
        began = time.monotonic()
        result = self.delayed[where].step(self.epoch, full)
        self.seconds["remote"] += time.monotonic() - began
        return result

    def _waited(self) -> float:
        """Seconds spent so far on messages that had not been written yet."""
        return sum(sync.ledger.waited for sync in self.delayed.values())

    def _layer(self, h: DataFrame, i: int) -> DataFrame:
        """(vid, part, a, z)."""
        width, (w, b) = self.dims[i], self.model.layers[i]
        total = self._sync(self._local(h, width), width, f"forward {i}")
        rows = total.join(h, ["part", "vid"]).join(self.roles.select("vid", "part", "norm"), ["part", "vid"])

        def run(batches):
            for batch in batches:
                if len(batch):
                    a = (_matrix(batch.column(2)) + _matrix(batch.column(3))) / batch.column(4).to_numpy()[:, None]
                    yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), _lists(a), _lists(a @ w + b)], names=["vid", "part", "a", "z"])

        return checkpointed(rows.select("vid", "part", "vec", "feat", "norm").mapInArrow(run, "vid long, part int, a array<double>, z array<double>"))

    def _loss_gradient(self, last: DataFrame) -> DataFrame:
        """(vid, part, a, dz, split, hit, loss) of the last layer."""
        n = max(1, self.n_train)

        def run(batches):
            for batch in batches:
                if len(batch):
                    p = softmax(_matrix(batch.column(3)))
                    y = batch.column(4).fill_null(0).to_numpy(zero_copy_only=False).astype(int)
                    split = np.array(batch.column(5).to_pylist(), dtype=object)
                    line, train = np.arange(len(y)), split == "train"
                    dz = p.copy()
                    dz[line, y] -= 1
                    dz *= train[:, None] / n
                    loss = np.where(train, -np.log(np.maximum(p[line, y], 1e-300)) / n, 0.0)
                    hit = (p.argmax(axis=1) == y).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), _lists(dz), batch.column(5), pa.array(hit), pa.array(loss)], names=["vid", "part", "a", "dz", "split", "hit", "loss"])

        rows = last.join(self.roles.select("vid", "part", "y", "split"), ["part", "vid"]).select("vid", "part", "a", "z", "y", "split")
        return checkpointed(rows.mapInArrow(run, "vid long, part int, a array<double>, dz array<double>, split string, hit int, loss double"))

    @staticmethod
    def _weight_gradient(rows: DataFrame, shape: tuple[int, int]) -> tuple[np.ndarray, np.ndarray]:
        """Sum over partitions of a' dz and of dz: each task sends one row to the driver."""

        def run(batches):
            dw, db = np.zeros(shape), np.zeros(shape[1])
            for batch in batches:
                if len(batch):
                    a, dz = _matrix(batch.column(0)), _matrix(batch.column(1))
                    dw += a.T @ dz
                    db += dz.sum(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array([dw.reshape(-1).tolist()]), pa.array([db.tolist()])], names=["dw", "db"])

        made = rows.select("a", "dz").mapInArrow(run, "dw array<double>, db array<double>").collect()
        return sum(np.array(r.dw) for r in made).reshape(shape), sum(np.array(r.db) for r in made)

    def gradients(self) -> tuple[list[tuple[np.ndarray, np.ndarray]], dict]:
        activations, h = [], self.h0
        for i in range(len(self.model.layers)):
            activations.append(self._layer(h, i))
            h = activations[-1].select("vid", "part", F.transform("z", lambda z: F.greatest(z, F.lit(0.0))).alias("feat"))
        top = self._loss_gradient(activations[-1])
        measured = top.where("split is not null").groupBy("split").agg(F.avg("hit").alias("accuracy"), F.sum("loss").alias("loss")).collect()
        grads, dz = [], top.select("vid", "part", "a", "dz")
        for i in range(len(self.model.layers) - 1, -1, -1):
            w, _ = self.model.layers[i]
            grads.insert(0, self._weight_gradient(dz, w.shape))
            if i:
                dz = self._back(dz, activations[i - 1], w, self.dims[i], i)
        return grads, {f"{r.split}_accuracy": r.accuracy for r in measured} | {"loss": sum(r.loss for r in measured)}

    def _back(self, dz: DataFrame, below: DataFrame, w: np.ndarray, width: int, i: int) -> DataFrame:
        """Gradient at the layer below: own part plus reversed local sums of the synchronised gradients."""

        def run(batches):
            for batch in batches:
                if len(batch):
                    g = _matrix(batch.column(2)) @ w.T / batch.column(3).to_numpy()[:, None]
                    yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), _lists(g)], names=["vid", "part", "vec"])

        rows = dz.join(self.roles.select("vid", "part", "norm"), ["part", "vid"]).select("vid", "part", "dz", "norm")
        own = checkpointed(rows.mapInArrow(run, "vid long, part int, vec array<double>"))
        synced = self._sync(own, width, f"backward {i}").withColumnRenamed("vec", "feat")
        sums = self._local(synced, width, "backward").withColumnRenamed("vec", "sums")
        rows = below.join(own, ["part", "vid"]).join(sums, ["part", "vid"], "left")
        total = F.zip_with("vec", F.coalesce("sums", F.array_repeat(F.lit(0.0), width)), lambda x, y: x + y)
        masked = F.zip_with(total, "z", lambda g, z: F.when(z > 0, g).otherwise(0.0))
        return checkpointed(rows.select("vid", "part", "a", masked.alias("dz")))

    def fit(self, epochs: int) -> list[dict]:
        for _ in range(epochs):
            began, waited = time.monotonic(), self._waited()
            self.seconds = {"local": 0.0, "remote": 0.0}
            grads, measured = self.gradients()
            self.optimiser.update(self.model, grads)
            timed = {"local_seconds": self.seconds["local"], "remote_seconds": self.seconds["remote"], "wait_seconds": self._waited() - waited}
            self.history.append({"epoch": self.epoch, "seconds": time.monotonic() - began, **timed, **measured})
            self.epoch += 1
        return self.history
