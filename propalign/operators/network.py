"""The dense network: two hidden layers, two outputs, mini-batches and a schedule of learning rates."""

from __future__ import annotations

from dataclasses import asdict, dataclass

import numpy as np


@dataclass(frozen=True)
class NetworkSpec:
    hidden: tuple[int, ...] = (128, 64)
    batch: int = 32
    #: (epochs, learning rate), one after the other.
    schedule: tuple[tuple[int, float], ...] = ((10, 1e-3), (5, 1e-4), (5, 1e-5))
    scale: str = "standard"  # or none
    seed: int = 7


@dataclass
class Network:
    spec: NetworkSpec
    mean: np.ndarray
    scale: np.ndarray
    weights: list[np.ndarray]
    biases: list[np.ndarray]

    activation: str = "rectified"  # or sigmoid, as Spark's perceptron has it

    def outputs(self, x: np.ndarray) -> np.ndarray:
        """The two outputs, which add up to 1: no match and match."""
        h = ((x - self.mean) / self.scale).astype(self.weights[0].dtype)
        for w, b in zip(self.weights[:-1], self.biases[:-1], strict=True):
            z = h @ w + b
            h = np.maximum(z, 0) if self.activation == "rectified" else 1 / (1 + np.exp(-np.clip(z, -35, 35)))
        z = h @ self.weights[-1] + self.biases[-1]
        z = np.exp(z - z.max(1, keepdims=True))
        return z / z.sum(1, keepdims=True)

    def score(self, x: np.ndarray) -> np.ndarray:
        return self.outputs(x)[:, 1].astype(float) if len(x) else np.zeros(0)

    def to_json(self) -> dict:
        return {"spec": asdict(self.spec), "activation": self.activation, "kind": str(self.weights[0].dtype), "mean": self.mean.tolist(), "scale": self.scale.tolist(), "weights": [w.tolist() for w in self.weights], "biases": [b.tolist() for b in self.biases]}

    @staticmethod
    def from_json(x: dict) -> Network:
        s = x["spec"]
        spec = NetworkSpec(tuple(s["hidden"]), s["batch"], tuple(map(tuple, s["schedule"])), s["scale"], s["seed"])
        arrays = lambda k: [np.array(w, dtype=x["kind"]) for w in x[k]]
        return Network(spec, np.array(x["mean"]), np.array(x["scale"]), arrays("weights"), arrays("biases"), x["activation"])


def fit(x: np.ndarray, y: np.ndarray, spec: NetworkSpec = NetworkSpec()) -> Network:
    """Rectified hidden layers, softmax cross-entropy, Adam. Same rows in the same order and the same seed give the same
    network. Without rows, the network answers 1/2."""
    rng = np.random.default_rng(spec.seed)
    width = x.shape[1]
    if spec.scale == "standard" and len(x):
        mean, scale = x.mean(0), x.std(0)
        scale = np.where(scale > 1e-9, scale, 1.0)
    else:
        mean, scale = np.zeros(width), np.ones(width)
    sizes = [width, *spec.hidden, 2]
    shapes = [*zip(sizes, sizes[1:], strict=False), *[(b,) for b in sizes[1:]]]
    n_layers = len(sizes) - 1
    # All weights and biases in one array, and so their gradients and moments: a step updates them by a dozen calls.
    params, weights, biases = _flat(shapes, n_layers)
    for w, (a, b) in zip(weights, shapes, strict=False):
        w[:] = rng.normal(size=(a, b)) * np.sqrt(2 / a)
    net = Network(spec, mean, scale, weights, biases)
    if not len(x):
        weights[-1][:] = 0
        return net
    data = ((x - mean) / scale).astype(np.float32)
    grads, grads_w, grads_b = _flat(shapes, n_layers)
    m, v, step, root = (np.zeros_like(params) for _ in range(4))
    wanted = np.zeros((len(data), 2), dtype=np.float32)
    wanted[np.arange(len(data)), y] = 1
    t = 0
    for epochs, rate in spec.schedule:
        for _ in range(epochs):
            order = rng.permutation(len(data))
            dealt, dealt_y = data[order], wanted[order]
            for at in range(0, len(order), spec.batch):
                acts = [dealt[at : at + spec.batch]]
                for i in range(n_layers):
                    z = acts[-1] @ weights[i]
                    z += biases[i]
                    acts.append(np.maximum(z, 0, out=z) if i < n_layers - 1 else z)
                delta = np.exp(z - z.max(1, keepdims=True))
                delta /= delta.sum(1, keepdims=True)
                delta -= dealt_y[at : at + spec.batch]
                delta /= len(delta)
                for i in range(n_layers - 1, -1, -1):
                    np.matmul(acts[i].T, delta, out=grads_w[i])
                    delta.sum(0, out=grads_b[i])
                    if i:
                        delta = delta @ weights[i].T
                        delta *= acts[i] > 0
                t += 1
                c1, c2 = 1 - 0.9**t, 1 - 0.999**t
                m *= 0.9
                m += np.multiply(grads, 0.1, out=step)
                v *= 0.999
                np.multiply(grads, 0.001, out=step)
                v += np.multiply(step, grads, out=step)
                np.sqrt(np.divide(v, c2, out=root), out=root)
                root += 1e-8
                np.multiply(m, rate / c1, out=step)
                params -= np.divide(step, root, out=step)
    return net


def _flat(shapes: list[tuple[int, ...]], n_layers: int) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray]]:
    """An array of zeros, and its parts in these shapes: weights of the layers, then their biases."""
    ends = np.cumsum([int(np.prod(s)) for s in shapes])
    flat = np.zeros(ends[-1], dtype=np.float32)
    parts = [p.reshape(s) for p, s in zip(np.split(flat, ends[:-1]), shapes, strict=True)]
    return flat, parts[:n_layers], parts[n_layers:]
