"""Forecasters behind one interface: parameters are a flat vector; forecast() and loss_grad() take arrays of contexts and targets."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np

from stratafit.models.tape import Var

Loss = Callable[[np.ndarray, list[Var]], Var]


def mse_loss(y: np.ndarray, out: list[Var]) -> Var:
    return (out[0] - Var(y)).square().mean()


def gaussian_nll_loss(y: np.ndarray, out: list[Var]) -> Var:
    """out is location and raw scale; the scale is its softplus and a small floor."""
    scale = out[1].softplus() + 1e-3
    z = (Var(y) - out[0]) / scale
    return (scale.log() + z.square() * 0.5 + 0.5 * math.log(2 * math.pi)).mean()


def student_nll_loss(df: float) -> Loss:
    const = math.lgamma(df / 2) - math.lgamma((df + 1) / 2) + 0.5 * math.log(df * math.pi)

    def loss(y: np.ndarray, out: list[Var]) -> Var:
        scale = out[1].softplus() + 1e-3
        z = (Var(y) - out[0]) / scale
        return (scale.log() + (z.square() * (1 / df)).log1p() * ((df + 1) / 2) + const).mean()

    return loss


def mape_loss(y: np.ndarray, out: list[Var], eps: float = 1e-8) -> Var:
    """Zero targets are left out."""
    keep = (np.abs(y) > eps).astype(float)
    weight = keep / np.maximum(np.abs(y), eps) / max(1.0, keep.sum())
    return ((out[0] - Var(y)).abs() * Var(weight)).sum()


def pinball_loss(q: float) -> Loss:
    def loss(y: np.ndarray, out: list[Var]) -> Var:
        e = Var(y) - out[0]
        return (e * q).maximum(e * (q - 1)).mean()

    return loss


class Forecaster:
    """shapes() lists the parameters; network() maps contexts to outputs."""

    def __init__(self, loss: Loss) -> None:
        self.loss = loss
        self.size = sum(math.prod(s) for _, s in self.shapes())

    def shapes(self) -> list[tuple[str, tuple[int, ...]]]:
        raise NotImplementedError

    def network(self, p: dict[str, Var], x: np.ndarray) -> list[Var]:
        raise NotImplementedError

    def start(self, seed: int = 0) -> np.ndarray:
        """Weights uniform within 1 / sqrt(inputs), biases 0."""
        rng = np.random.default_rng(seed)
        return np.concatenate([(rng.uniform(-1, 1, s) / math.sqrt(s[0]) if len(s) > 1 else np.zeros(s)).ravel() for _, s in self.shapes()])

    def _unpack(self, theta: np.ndarray) -> dict[str, Var]:
        out, at = {}, 0
        for name, s in self.shapes():
            n = math.prod(s)
            out[name] = Var(theta[at : at + n].reshape(s))
            at += n
        return out

    def forecast(self, theta: np.ndarray, x: np.ndarray) -> list[np.ndarray]:
        return [v.value for v in self.network(self._unpack(theta), np.asarray(x, float))]

    def loss_grad(self, theta: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
        p = self._unpack(theta)
        loss = self.loss(np.asarray(y, float), self.network(p, np.asarray(x, float)))
        loss.backward()
        return float(loss.value), np.concatenate([(v.grad if v.grad is not None else np.zeros_like(v.value)).ravel() for v in p.values()])

    def loss_only(self, theta: np.ndarray, x: np.ndarray, y: np.ndarray) -> float:
        return float(self.loss(np.asarray(y, float), self.network(self._unpack(theta), np.asarray(x, float))).value)


class ARModel(Forecaster):
    """The next value as a weighted sum of the last p; the first weight belongs to the newest."""

    def __init__(self, p: int, loss: Loss = mse_loss) -> None:
        self.p = p
        super().__init__(loss)

    def shapes(self) -> list[tuple[str, tuple[int, ...]]]:
        return [("w", (self.p, 1))]

    def network(self, p: dict[str, Var], x: np.ndarray) -> list[Var]:
        return [Var(x[:, ::-1][:, : self.p]) @ p["w"]]


class VARModel(Forecaster):
    """Vectors of n series: contexts are (batch, p * n), newest vector first."""

    def __init__(self, p: int, n: int, loss: Loss = mse_loss) -> None:
        self.p, self.n = p, n
        super().__init__(loss)

    def shapes(self) -> list[tuple[str, tuple[int, ...]]]:
        return [("w", (self.p * self.n, self.n))]

    def network(self, p: dict[str, Var], x: np.ndarray) -> list[Var]:
        return [Var(x) @ p["w"]]


class MLPModel(Forecaster):
    """depth hidden layers of ReLU; one head per output (location, or location and scale)."""

    def __init__(self, tau_c: int, tau_p: int, hidden: int = 80, depth: int = 4, heads: int = 2, loss: Loss = gaussian_nll_loss) -> None:
        self.tau_c, self.tau_p, self.hidden, self.depth, self.heads = tau_c, tau_p, hidden, depth, heads
        super().__init__(loss)

    def shapes(self) -> list[tuple[str, tuple[int, ...]]]:
        out, width = [], self.tau_c
        for i in range(self.depth):
            out += [(f"w{i}", (width, self.hidden)), (f"b{i}", (self.hidden,))]
            width = self.hidden
        for h in range(self.heads):
            out += [(f"v{h}", (width, self.tau_p)), (f"c{h}", (self.tau_p,))]
        return out

    def network(self, p: dict[str, Var], x: np.ndarray) -> list[Var]:
        h = Var(x)
        for i in range(self.depth):
            h = (h @ p[f"w{i}"] + p[f"b{i}"]).relu()
        return [h @ p[f"v{k}"] + p[f"c{k}"] for k in range(self.heads)]


class LSTMModel(Forecaster):
    """depth layers of hidden cells over one value a step; the last hidden state forecasts tau_p steps."""

    def __init__(self, tau_c: int, tau_p: int, hidden: int = 100, depth: int = 2, loss: Loss = mse_loss) -> None:
        self.tau_c, self.tau_p, self.hidden, self.depth = tau_c, tau_p, hidden, depth
        super().__init__(loss)

    def shapes(self) -> list[tuple[str, tuple[int, ...]]]:
        out, width = [], 1
        for i in range(self.depth):
            out += [(f"x{i}", (width, 4 * self.hidden)), (f"h{i}", (self.hidden, 4 * self.hidden)), (f"b{i}", (4 * self.hidden,))]
            width = self.hidden
        return [*out, ("v", (width, self.tau_p)), ("c", (self.tau_p,))]

    def network(self, p: dict[str, Var], x: np.ndarray) -> list[Var]:
        n, k = self.hidden, x.shape[0]
        state = [(Var(np.zeros((k, n))), Var(np.zeros((k, n)))) for _ in range(self.depth)]
        for t in range(x.shape[1]):
            signal = Var(x[:, t : t + 1])
            for i, (h, c) in enumerate(state):
                z = signal @ p[f"x{i}"] + h @ p[f"h{i}"] + p[f"b{i}"]
                c = z[:, n : 2 * n].sigmoid() * c + z[:, :n].sigmoid() * z[:, 2 * n : 3 * n].tanh()
                h = z[:, 3 * n :].sigmoid() * c.tanh()
                state[i] = (h, c)
                signal = h
        return [state[-1][0] @ p["v"] + p["c"]]


class ResidualStackModel(Forecaster):
    """Stacked blocks of fully connected layers: each takes its backcast from the input that goes on, and adds its forecast."""

    def __init__(self, tau_c: int, tau_p: int, stacks: int = 30, width: int = 32, layers: int = 4, loss: Loss = mape_loss) -> None:
        self.tau_c, self.tau_p, self.stacks, self.width, self.layers = tau_c, tau_p, stacks, width, layers
        super().__init__(loss)

    def shapes(self) -> list[tuple[str, tuple[int, ...]]]:
        out = []
        for s in range(self.stacks):
            width = self.tau_c
            for i in range(self.layers):
                out += [(f"w{s}.{i}", (width, self.width)), (f"b{s}.{i}", (self.width,))]
                width = self.width
            out += [(f"back{s}", (width, self.tau_c)), (f"fore{s}", (width, self.tau_p)), (f"c{s}", (self.tau_p,))]
        return out

    def network(self, p: dict[str, Var], x: np.ndarray) -> list[Var]:
        rest, total = Var(x), None
        for s in range(self.stacks):
            h = rest
            for i in range(self.layers):
                h = (h @ p[f"w{s}.{i}"] + p[f"b{s}.{i}"]).relu()
            fore = h @ p[f"fore{s}"] + p[f"c{s}"]
            total = fore if total is None else total + fore
            rest = rest - h @ p[f"back{s}"]
        return [total]
