"""A small convolutional classifier with long short-term memory for activity windows, in numpy.

One convolution over time with rectified outputs, one recurrent layer of memory cells, two
classes by softmax; cross-entropy, adaptive gradient steps. Training is on the driver
over a bounded sample of windows; scoring is distributed, weights broadcast, windows
in Arrow batches.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Windows to train on at most.
SAMPLE = 4000


def _sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


class Net:
    """Parameters and passes; x is (windows, steps, channels)."""

    def __init__(self, channels: int, filters: int = 16, kernel: int = 5, hidden: int = 32, pool: int = 4, seed: int = 3):
        rng = np.random.default_rng(seed)
        glorot = lambda a, b: rng.normal(size=(a, b)) * np.sqrt(2 / (a + b))
        self.kernel, self.pool, self.hidden = kernel, pool, hidden
        self.p = {
            "wc": glorot(kernel * channels, filters), "bc": np.zeros(filters), "wx": glorot(filters, 4 * hidden), "wh": glorot(hidden, 4 * hidden),
            # Cells start by keeping what they hold.
            "bh": np.repeat([0.0, 1.0, 0.0, 0.0], hidden), "wo": glorot(hidden, 2), "bo": np.zeros(2),
        }

    def forward(self, x: np.ndarray):
        p, k, h = self.p, self.kernel, self.hidden
        view = np.lib.stride_tricks.sliding_window_view(x, k, axis=1)  # (n, t, channels, kernel)
        cols = view.transpose(0, 1, 3, 2).reshape(len(x), view.shape[1], -1)
        a = cols @ p["wc"] + p["bc"]
        r = np.maximum(a, 0)
        t = r.shape[1] // self.pool
        z = r[:, : t * self.pool].reshape(len(x), t, self.pool, -1).mean(axis=2)
        s, cell, steps = np.zeros((len(x), h)), np.zeros((len(x), h)), []
        for i in range(t):
            gates = z[:, i] @ p["wx"] + s @ p["wh"] + p["bh"]
            take, hold, show = (_sigmoid(gates[:, k * h : (k + 1) * h]) for k in range(3))
            new = np.tanh(gates[:, 3 * h :])
            grown = hold * cell + take * new
            seen = np.tanh(grown)
            steps.append((s, cell, take, hold, show, new, seen))
            s, cell = show * seen, grown
        o = s @ p["wo"] + p["bo"]
        e = np.exp(o - o.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True), (cols, a, z, t, steps, s)

    def gradient(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        p = self.p
        prob, (cols, a, z, t, steps, s) = self.forward(x)
        n = len(x)
        loss = -np.log(np.maximum(prob[np.arange(n), y], 1e-12)).mean()
        d = prob.copy()
        d[np.arange(n), y] -= 1
        d /= n
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["wo"], g["bo"] = s.T @ d, d.sum(axis=0)
        ds, dc, dz = d @ p["wo"].T, 0.0, np.zeros_like(z)
        for i in range(t - 1, -1, -1):
            s0, c0, take, hold, show, new, seen = steps[i]
            dc = dc + ds * show * (1 - seen**2)
            dg = np.concatenate([dc * new * take * (1 - take), dc * c0 * hold * (1 - hold), ds * seen * show * (1 - show), dc * take * (1 - new**2)], axis=1)
            g["wx"] += z[:, i].T @ dg
            g["bh"] += dg.sum(axis=0)
            g["wh"] += s0.T @ dg
            dz[:, i] = dg @ p["wx"].T
            ds, dc = dg @ p["wh"].T, dc * hold
        dr = np.zeros_like(a)
        dr[:, : t * self.pool] = np.repeat(dz / self.pool, self.pool, axis=1)
        da = dr * (a > 0)
        g["wc"], g["bc"] = cols.reshape(-1, cols.shape[2]).T @ da.reshape(-1, da.shape[2]), da.sum(axis=(0, 1))
        return loss, g


class ConvRecurrentClassifier:
    """fit(windows) and transform(windows); windows have ``sample`` (array of structs or numbers) and label Pick / NoPick."""

    def __init__(self, channels: int = 4, filters: int = 16, kernel: int = 5, hidden: int = 32, epochs: int = 50, batch: int = 64, rate: float = 3e-3, seed: int = 3, features: tuple[str, ...] | None = None):
        self.channels, self.epochs, self.batch, self.rate, self.seed, self.features = channels, epochs, batch, rate, seed, features
        self.net = Net(channels, filters, kernel, hidden, seed=seed)
        self.mean, self.std = np.zeros(channels), np.ones(channels)

    def _column(self):
        """Each window as a flat array of doubles."""
        if self.features is None:
            return F.transform("sample", lambda s: s.cast("double"))
        return F.flatten(F.transform("sample", lambda s: F.array(*[s[f].cast("double") for f in self.features])))

    def fit_arrays(self, x: np.ndarray, y: np.ndarray) -> ConvRecurrentClassifier:
        self.mean, self.std = x.mean(axis=(0, 1)), x.std(axis=(0, 1)) + 1e-9
        x = (x - self.mean) / self.std
        rng = np.random.default_rng(self.seed)
        m = {k: np.zeros_like(v) for k, v in self.net.p.items()}
        v = {k: np.zeros_like(w) for k, w in self.net.p.items()}
        step = 0
        for _ in range(self.epochs):
            order = rng.permutation(len(x))
            for s in range(0, len(x), self.batch):
                at = order[s : s + self.batch]
                _, g = self.net.gradient(x[at], y[at])
                step += 1
                for k in g:
                    m[k] = 0.9 * m[k] + 0.1 * g[k]
                    v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                    self.net.p[k] -= self.rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        return self

    def fit(self, windows: DataFrame, sample: int = SAMPLE) -> ConvRecurrentClassifier:
        rows = windows.select(self._column().alias("x"), "label").orderBy(F.xxhash64(F.col("x"))).limit(sample).collect()
        size = max((len(r.x) for r in rows), default=0)
        rows = [r for r in rows if len(r.x) == size]
        x = np.array([r.x for r in rows]).reshape(len(rows), -1, self.channels)
        return self.fit_arrays(x, np.array([int(r.label == "Pick") for r in rows]))

    def score_arrays(self, x: np.ndarray) -> np.ndarray:
        return self.net.forward((x - self.mean) / self.std)[0][:, 1]

    def transform(self, windows: DataFrame) -> DataFrame:
        """+ score (probability of Pick), predicted. Every window that the network can take is scored, the others get 0; a window's score depends on nothing but itself."""
        shared = windows.sparkSession.sparkContext.broadcast(self)
        names = windows.columns
        flat = windows.withColumn("_x", self._column())
        schema = windows.withColumn("score", F.lit(0.0)).schema

        def run(batches):
            model = shared.value
            for batch in batches:
                xs = batch.column(len(names)).to_pylist()
                score = np.zeros(len(xs))
                least = (model.net.kernel + model.net.pool - 1) * model.channels
                for n, ks in itertools.groupby(sorted(range(len(xs)), key=lambda k: len(xs[k])), key=lambda k: len(xs[k])):
                    ks = list(ks)
                    if n >= least:
                        score[ks] = model.score_arrays(np.array([xs[k] for k in ks]).reshape(len(ks), -1, model.channels))
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(score)], names=[*names, "score"])

        return flat.mapInArrow(run, schema).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def windows_from_embeddings(embeddings: DataFrame) -> DataFrame:
    """One-channel windows; the labels carry no signal, so only shape and throughput are tested."""
    return embeddings.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("sample"), F.when(F.col("label") < 5, "Pick").otherwise("NoPick").alias("label"))


FEATURES = {"mass": ("w",), "acceleration": ("ax", "ay", "az"), "velocity": ("vel",)}


def feature_ablation(windows: DataFrame, epochs: int = 50, sample: int = SAMPLE) -> DataFrame:
    """subset, precision, recall, f1, accuracy on every second cart, for each of the seven subsets of mass, acceleration and velocity."""
    from .metrics import confusion

    out = None
    for n in range(1, len(FEATURES) + 1):
        for names in itertools.combinations(FEATURES, n):
            cols = tuple(c for f in names for c in FEATURES[f])
            model = ConvRecurrentClassifier(len(cols), epochs=epochs, features=cols).fit(windows.where("pmod(cart_id, 2) = 0"), sample)
            scored = model.transform(windows.where("pmod(cart_id, 2) = 1"))
            one = confusion(scored, (F.col("label") == "Pick").cast("int"), F.col("predicted")).select(F.lit("+".join(names)).alias("subset"), "precision", "recall", "f1", "accuracy")
            out = one if out is None else out.unionByName(one)
    return out


class SummaryBaseline:
    """Classifiers on window summaries: logistic, forest, boosted trees, perceptron."""

    def __init__(self, kind: str = "logistic"):
        self.kind = kind

    def _features(self, windows: DataFrame) -> DataFrame:
        from pyspark.ml.feature import VectorAssembler

        w = F.transform("sample", lambda s: s["w"])
        mean = F.aggregate(w, F.lit(0.0), lambda a, x: a + x) / F.size(w)
        out = windows.withColumns({"_rise": F.element_at(w, -1) - w[0], "_mean": mean, "_range": F.array_max(w) - F.array_min(w), "_y": (F.col("label") == "Pick").cast("double")})
        return VectorAssembler(inputCols=["_rise", "_mean", "_range"], outputCol="_features").transform(out)

    def fit(self, windows: DataFrame) -> SummaryBaseline:
        from pyspark.ml import classification as c

        kinds = {
            "logistic": lambda **k: c.LogisticRegression(**k), "forest": lambda **k: c.RandomForestClassifier(seed=1, **k), "boosted": lambda **k: c.GBTClassifier(seed=1, **k),
            "perceptron": lambda **k: c.MultilayerPerceptronClassifier(layers=[3, 8, 2], seed=1, **k),
        }
        self.model = kinds[self.kind](featuresCol="_features", labelCol="_y", predictionCol="_p").fit(self._features(windows))
        return self

    def transform(self, windows: DataFrame) -> DataFrame:
        return self.model.transform(self._features(windows)).select(*windows.columns, F.col("_p").cast("int").alias("predicted"))
