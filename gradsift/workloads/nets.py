"""Small nets in numpy: a perceptron, a gated recurrent net over characters,
and a factor model with a perceptron for recommendation.

A net is a list of named layers and a function from flat parameters and a
batch to loss and flat gradient. In data-parallel training each worker holds
a replica, so the parameters of a net fit a worker by construction. Not so
the factors of a recommender, of which a batch uses a few: FactorWorkload
makes a net of those alone.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np


#: Sequences whose symbols are predicted side by side.
ROWS = 256
#: Outputs within this bound have exponentials that single precision can add.
EXPONENT = 60.0
#: Initial values that are drawn at once.
PIECE = 1 << 18


def _unmarked() -> None:
    pass


@dataclass(frozen=True)
class Net:
    layers: tuple[tuple[str, tuple[int, ...]], ...]

    @property
    def sizes(self) -> list[tuple[str, int]]:
        return [(name, int(np.prod(shape))) for name, shape in self.layers]

    @property
    def n_g(self) -> int:
        return sum(size for _, size in self.sizes)

    def cut(self, flat: np.ndarray) -> list[np.ndarray]:
        out, at = [], 0
        for (_, shape), (_, size) in zip(self.layers, self.sizes, strict=True):
            out.append(flat[at : at + size].reshape(shape))
            at += size
        return out

    def pieces(self, seed: int, width: int = PIECE) -> Iterator[tuple[int, int, float, dict]]:
        """(start, size, scale, state of the generator) of every run of initial
        values: drawn() makes one without those before it. The generator walks
        through its whole stream, with one piece in memory."""
        rng, room, at = np.random.default_rng(seed), np.empty(width), 0
        for (name, shape), (_, size) in zip(self.layers, self.sizes, strict=True):
            scale = 0.0 if len(shape) == 1 else 1 / np.sqrt(shape[0] if not name.startswith("embed") else shape[1])
            for lo in range(0, size, width):
                n = min(width, size - lo)
                yield at + lo, n, float(scale), rng.bit_generator.state
                if scale:
                    rng.standard_normal(out=room[:n])
            at += size

    def init(self, seed: int) -> np.ndarray:
        return np.concatenate([drawn(size, scale, state) for _, size, scale, state in self.pieces(seed)])

    def loss(self, flat: np.ndarray, batch: tuple, mark: Callable[[], None] = _unmarked) -> tuple[float, np.ndarray]:
        """Mean loss of a batch and its gradient; mark is called between the
        forward and the backward pass."""
        raise NotImplementedError


def drawn(size: int, scale: float, state: dict) -> np.ndarray:
    """A piece of initial values; a scale of 0 stands for zeros."""
    if not scale:
        return np.zeros(size)
    rng = np.random.default_rng(0)
    rng.bit_generator.state = state
    return rng.normal(0, scale, size)


def softmax_loss(z: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """Mean negative log likelihood and its gradient."""
    z = z - z.max(axis=1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(axis=1, keepdims=True)
    at = np.arange(len(y))
    nll = -np.log(np.maximum(p[at, y], 1e-300)).mean()
    p[at, y] -= 1
    return nll, p / len(y)


class Perceptron(Net):
    """Fully connected layers with rectifiers and a softmax."""

    def __init__(self, widths: tuple[int, ...]):
        layers = []
        for i, (a, b) in enumerate(zip(widths[:-1], widths[1:], strict=True)):
            layers += [(f"w{i}", (a, b)), (f"b{i}", (b,))]
        super().__init__(tuple(layers))

    def _forward(self, flat: np.ndarray, x: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
        parts, seen = self.cut(flat), [x]
        for i in range(0, len(parts), 2):
            x = x @ parts[i] + parts[i + 1]
            if i + 2 < len(parts):
                x = np.maximum(x, 0)
            seen.append(x)
        return parts, seen

    def loss(self, flat, batch, mark=_unmarked):
        x, y = batch
        parts, seen = self._forward(flat, x)
        nll, d = softmax_loss(seen[-1], y)
        mark()
        grads = []
        for i in range(len(parts) - 2, -1, -2):
            grads = [seen[i // 2].T @ d, d.sum(axis=0), *grads]
            d = (d @ parts[i].T) * (seen[i // 2] > 0)
        return nll, np.concatenate([g.reshape(-1) for g in grads])

    def predict(self, flat: np.ndarray, x: np.ndarray) -> np.ndarray:
        return self._forward(flat, x)[1][-1].argmax(axis=1)


class Recurrent(Net):
    """One recurrent layer with input, forget and output gates and a
    candidate, each a layer of its own, over embedded symbols."""

    GATES = ("in", "forget", "out", "cand")

    def __init__(self, symbols: int, embed: int = 32, hidden: int = 64):
        layers = [("embed", (symbols, embed))]
        for g in self.GATES:
            layers += [(f"x_{g}", (embed, hidden)), (f"h_{g}", (hidden, hidden)), (f"b_{g}", (hidden,))]
        super().__init__((*layers, ("out", (hidden, symbols)), ("out_b", (symbols,))))

    def nll(self, flat: np.ndarray, s: np.ndarray, y: np.ndarray) -> float:
        """Mean negative log likelihood of the next symbols, forward only:
        what a symbol adds to the gates looked up, and few enough rows at once
        to stay in a core's cache. Layers are in single precision, sums in
        double: the mean is right to about eight digits."""
        p = self.cut(flat)
        embed, gates, out, out_b = p[0], [p[1 + 3 * i : 4 + 3 * i] for i in (3, 0, 1, 2)], p[-2], p[-1]
        if s.size and not 0 <= s.min() <= s.max() < len(embed):
            raise IndexError("a symbol is not one of the net's")
        # the logistic function of v is (1 + tanh(v / 2)) / 2; the last half
        # is in the layers that read the hidden state
        half = np.array([1.0, 0.5, 0.5, 0.5])[:, None, None]
        seen = (np.stack([embed @ wx + b for wx, _, b in gates]) + np.array([0.0, 0.0, 1.0, 0.0])[:, None, None]) * half
        wh = np.stack([wh for _, wh, _ in gates]) * half / 2
        # hidden values are within 1, so outputs are within this bound
        bounded = float(np.abs(out).sum(axis=0).max() + np.abs(out_b).max()) < EXPONENT
        seen, wh, out, out_b = (x.astype(np.float32) for x in (seen, wh, out / 2, out_b))
        return sum(self._sum_nll(s[lo : lo + ROWS].T, y[lo : lo + ROWS].T, seen, wh, out, out_b, bounded) for lo in range(0, len(s), ROWS)) / s.size

    @staticmethod
    def _sum_nll(s: np.ndarray, y: np.ndarray, seen: np.ndarray, wh: np.ndarray, out: np.ndarray, out_b: np.ndarray, bounded: bool) -> float:
        """s, y: (steps, rows). bounded: no exponential of an output overflows."""
        (steps, rows), n = s.shape, out.shape[0]
        a, own_seen = np.empty((4, rows, n), np.float32), np.empty((4, rows, n), np.float32)
        c, h, z = np.zeros((rows, n), np.float32), np.empty((rows, n), np.float32), np.empty((rows, out.shape[1]), np.float32)
        mass, own, at, scale = np.empty((steps, rows), np.float32), np.empty((steps, rows), np.float32), np.arange(rows), np.exp(out_b if bounded else 0 * out_b)
        for t in range(steps):
            np.take(seen, s[t], axis=1, out=own_seen if t else a, mode="clip")
            if t:
                np.matmul(h, wh, out=a)
                a += own_seen
            np.tanh(a, out=a)
            cand, enter, keep, leave = a
            a[1:] += 1
            c *= keep
            enter *= cand
            c += enter
            c *= 0.5
            np.tanh(c, out=h)
            h *= leave
            np.dot(h, out, out=z)
            if not bounded:
                z += out_b
                z -= z.max(axis=1, keepdims=True)
            own[t] = z[at, y[t]]
            np.exp(z, out=z)
            np.dot(z, scale, out=mass[t])
        given = float(out_b[y].sum(dtype=np.float64)) if bounded else 0.0
        return float(np.log(mass).sum(dtype=np.float64)) - float(own.sum(dtype=np.float64)) - given

    def loss(self, flat, batch, mark=_unmarked):
        s, y = batch  # symbols and next symbols, (rows, steps)
        p = self.cut(flat)
        embed, gates, out, out_b = p[0], [p[1 + 3 * i : 4 + 3 * i] for i in range(4)], p[-2], p[-1]
        rows, steps = s.shape
        h, c, kept = np.zeros((rows, out.shape[0])), np.zeros((rows, out.shape[0])), []
        hs = []
        for t in range(steps):
            e = embed[s[:, t]]
            a = [e @ wx + h @ wh + b for wx, wh, b in gates]
            i, f, o = (1 / (1 + np.exp(-v)) for v in (a[0], a[1] + 1, a[2]))
            g = np.tanh(a[3])
            before = (h, c)
            c = f * c + i * g
            h = o * np.tanh(c)
            kept.append((e, i, f, o, g, c, *before))
            hs.append(h)
        z = np.stack(hs, axis=1).reshape(-1, out.shape[0])
        nll, d = softmax_loss(z @ out + out_b, y.reshape(-1))
        mark()
        g_out, g_out_b = z.T @ d, d.sum(axis=0)
        dz = (d @ out.T).reshape(rows, steps, -1)
        g_embed = np.zeros_like(embed)
        g_gates = [[np.zeros_like(w) for w in gate] for gate in gates]
        dh, dc = np.zeros_like(h), np.zeros_like(c)
        for t in range(steps - 1, -1, -1):
            e, i, f, o, g, c, h0, c0 = kept[t]
            dh = dh + dz[:, t]
            th = np.tanh(c)
            dc = dc + dh * o * (1 - th * th)
            da = [dc * g * i * (1 - i), dc * c0 * f * (1 - f), dh * th * o * (1 - o), dc * i * (1 - g * g)]
            de, dh = np.zeros_like(e), np.zeros_like(dh)
            for (wx, wh, _), (gx, gh, gb), v in zip(gates, g_gates, da, strict=True):
                gx += e.T @ v
                gh += h0.T @ v
                gb += v.sum(axis=0)
                de += v @ wx.T
                dh += v @ wh.T
            dc = dc * f
            np.add.at(g_embed, s[:, t], de)
        flat_gates = [w.reshape(-1) for gate in g_gates for w in gate]
        return nll, np.concatenate([g_embed.reshape(-1), *flat_gates, g_out.reshape(-1), g_out_b])


class Recommender(Net):
    """Product of user and item factors beside a perceptron on both, with a
    logistic loss on bought against drawn pairs."""

    #: Values of a user or item in one of its two layers.
    WIDTH = 8

    def __init__(self, users: int, items: int, width: int = WIDTH):
        layers = [("embed_user_product", (users, width)), ("embed_item_product", (items, width)), ("embed_user_net", (users, width)), ("embed_item_net", (items, width))]
        layers += [("w0", (2 * width, 2 * width)), ("b0", (2 * width,)), ("w1", (2 * width, width)), ("b1", (width,)), ("out", (2 * width, 1)), ("out_b", (1,))]
        super().__init__(tuple(layers))

    def _forward(self, flat, u, i):
        p = self.cut(flat)
        product = p[0][u] * p[1][i]
        x0 = np.concatenate([p[2][u], p[3][i]], axis=1)
        x1 = np.maximum(x0 @ p[4] + p[5], 0)
        x2 = np.maximum(x1 @ p[6] + p[7], 0)
        top = np.concatenate([product, x2], axis=1)
        return p, product, x0, x1, x2, top, (top @ p[8] + p[9])[:, 0]

    def loss(self, flat, batch, mark=_unmarked):
        u, i, y = batch
        p, product, x0, x1, x2, top, z = self._forward(flat, u, i)
        nll = np.mean(np.logaddexp(0, z) - y * z)
        mark()
        d = ((1 / (1 + np.exp(-z)) - y) / len(y))[:, None]
        width = product.shape[1]
        g_out, g_out_b, dtop = top.T @ d, d.sum(axis=0), d @ p[8].T
        d2 = dtop[:, width:] * (x2 > 0)
        d1 = (d2 @ p[6].T) * (x1 > 0)
        d0 = d1 @ p[4].T
        grads = [np.zeros_like(w) for w in p[:4]]
        np.add.at(grads[0], u, dtop[:, :width] * p[1][i])
        np.add.at(grads[1], i, dtop[:, :width] * p[0][u])
        np.add.at(grads[2], u, d0[:, :width])
        np.add.at(grads[3], i, d0[:, width:])
        rest = [x0.T @ d1, d1.sum(axis=0), x1.T @ d2, d2.sum(axis=0), g_out, g_out_b]
        return nll, np.concatenate([g.reshape(-1) for g in [*grads, *rest]])

    def score(self, flat, u, i) -> np.ndarray:
        return self._forward(flat, u, i)[-1]
