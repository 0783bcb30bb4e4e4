"""Small bidirectional recurrent layers in numpy: a gated recurrent unit over symbols and an LSTM over vectors.

Both run their two directions as one stacked batch, time step by time step, and are trained by backpropagation through
time with Adam. Sequences are arrays (time, batch); the backward direction reads them reversed.
"""

from __future__ import annotations

import numpy as np


class Adam:
    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.params, self.rate, self.t = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: dict[str, np.ndarray], clip: float = 5.0) -> None:
        self.t += 1
        norm = np.sqrt(sum(float((g * g).sum()) for g in grads.values()))
        scale = min(1.0, clip / (norm + 1e-9))
        for k, g in grads.items():
            g = g * scale
            self.m[k] += 0.1 * (g - self.m[k])
            self.v[k] += 0.001 * (g * g - self.v[k])
            m, v = self.m[k] / (1 - 0.9**self.t), self.v[k] / (1 - 0.999**self.t)
            self.params[k] -= (self.rate * m / (np.sqrt(v) + 1e-8)).astype(np.float32)


def sigmoid(x: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
    out = np.multiply(x, np.float32(0.5), out=out)
    np.tanh(out, out=out)
    out *= np.float32(0.5)
    out += np.float32(0.5)
    return out


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


class BiGru:
    """Symbols (time, batch) in, class logits (time, batch, classes) out."""

    def __init__(self, symbols: int, hidden: int, classes: int, seed: int = 1):
        rng = np.random.default_rng(seed)
        r = lambda *s, scale: (rng.standard_normal(s) * scale).astype(np.float32)
        self.hidden = hidden
        self.p = {
            "x": r(2, symbols, 3 * hidden, scale=0.3), "u": r(2, hidden, 3 * hidden, scale=hidden**-0.5), "bn": np.zeros((2, 1, hidden), np.float32),
            "o": r(2, hidden, classes, scale=hidden**-0.5), "c": np.zeros(classes, np.float32),
        }

    def states(self, ids: np.ndarray, keep: list | None = None) -> np.ndarray:
        """Hidden states (time, 2, batch, hidden), the backward ones at their own reading order."""
        t, b, h, p = *ids.shape, self.hidden, self.p
        state = np.zeros((2, b, h), np.float32)
        out = np.empty((t, 2, b, h), np.float32)
        for k in range(t):
            x = np.stack([p["x"][0].take(ids[k], axis=0), p["x"][1].take(ids[t - 1 - k], axis=0)])
            a = np.matmul(state, p["u"])
            gates = x[..., : 2 * h] + a[..., : 2 * h]
            sigmoid(gates, gates)
            z, r = gates[..., :h], gates[..., h:]
            an = a[..., 2 * h :] + p["bn"]
            n = np.tanh(x[..., 2 * h :] + r * an)
            if keep is not None:
                keep.append((state, z, r, an, n))
            state = n + z * (state - n)
            out[k] = state
        return out

    def logits(self, states: np.ndarray) -> np.ndarray:
        return np.matmul(states[:, 0], self.p["o"][0]) + np.matmul(states[::-1, 1], self.p["o"][1]) + self.p["c"]

    def gradients(self, ids: np.ndarray, target: np.ndarray, weight: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean cross-entropy of target (time, batch) under weight, and its gradients by backpropagation through time."""
        t, b, h, p = *ids.shape, self.hidden, self.p
        keep: list = []
        states = self.states(ids, keep)
        prob = softmax(self.logits(states))
        hit = np.take_along_axis(prob, target[..., None], axis=-1)[..., 0]
        loss = float((-np.log(hit + 1e-12) * weight).sum() / weight.sum())
        d = prob
        np.put_along_axis(d, target[..., None], np.take_along_axis(d, target[..., None], -1) - 1, -1)
        d *= (weight / weight.sum())[..., None]
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["c"] = d.sum(axis=(0, 1))
        back = d[::-1]
        for s, e in ((0, d), (1, back)):
            g["o"][s] = np.einsum("tbh,tbc->hc", states[:, s], e, optimize=True)
        dh = np.zeros((2, b, h), np.float32)
        for k in range(t - 1, -1, -1):
            dh += np.stack([d[k] @ p["o"][0].T, back[k] @ p["o"][1].T])
            state, z, r, an, n = keep[k]
            dz = dh * (state - n) * z * (1 - z)
            dn = dh * (1 - z) * (1 - n * n)
            dr = dn * an * r * (1 - r)
            da = np.concatenate([dz, dr, dn * r], axis=-1)
            dx = np.concatenate([dz, dr, dn], axis=-1)
            g["bn"] += (dn * r).sum(axis=1, keepdims=True)
            g["u"] += np.matmul(state.transpose(0, 2, 1), da)
            for s, row in ((0, ids[k]), (1, ids[t - 1 - k])):
                np.add.at(g["x"][s], row, dx[s])
            dh = dh * z + np.matmul(da, p["u"].transpose(0, 2, 1))
        return loss, g


class BiLstm:
    """Vectors (time, batch, width) in, one logit a step (time, batch) out."""

    def __init__(self, width: int, hidden: int, seed: int = 1):
        rng = np.random.default_rng(seed)
        r = lambda *s, scale: (rng.standard_normal(s) * scale).astype(np.float32)
        self.hidden = hidden
        b = np.zeros((2, 1, 4 * hidden), np.float32)
        b[..., hidden : 2 * hidden] = 1  # the forget gates start open
        self.p = {"x": r(2, width, 4 * hidden, scale=width**-0.5), "u": r(2, hidden, 4 * hidden, scale=hidden**-0.5), "b": b, "o": r(2, hidden, scale=hidden**-0.5), "s": np.zeros(width, np.float32), "c": np.zeros(1, np.float32)}

    def _run(self, x: np.ndarray, mask: np.ndarray, keep: dict | None) -> np.ndarray:
        """Hidden states (time, 2, batch, hidden), the backward ones at their own reading order; where the mask is zero a state stays as it is."""
        t, b, h, p = *x.shape[:2], self.hidden, self.p
        scale = np.repeat(np.float32([0.5, 1]), (3 * h, h))  # the logistic function is a halved and lifted tanh of half its input
        inner, u = np.empty((t, 2, b, 4 * h), np.float32), p["u"] * scale
        np.matmul(x, p["x"][0] * scale, out=inner[:, 0])
        np.matmul(x[::-1], p["x"][1] * scale, out=inner[:, 1])
        inner += p["b"] * scale
        live = np.stack([mask, mask[::-1]], axis=1)[..., None] > 0
        state, cell = np.zeros((2, b, h), np.float32), np.zeros((2, b, h), np.float32)
        out = np.empty((t, 2, b, h), np.float32)
        cells, tops = (np.empty_like(out), np.empty_like(out)) if keep is not None else (None, None)
        for k in range(t):
            a = inner[k]  # becomes the gates and the candidate
            a += np.matmul(state, u)
            np.tanh(a, out=a)
            gates = a[..., : 3 * h]
            gates *= np.float32(0.5)
            gates += np.float32(0.5)
            new = a[..., h : 2 * h] * cell
            new += a[..., :h] * a[..., 3 * h :]
            top = np.tanh(new)
            if keep is not None:
                cells[k], tops[k] = cell, top
            cell = np.where(live[k], new, cell)
            state = np.where(live[k], a[..., 2 * h : 3 * h] * top, state)
            out[k] = state
        if keep is not None:
            keep.update(inner=inner, cells=cells, tops=tops, live=live)
        return out

    def one_way(self, x: np.ndarray, way: int, last: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, tuple[np.ndarray, np.ndarray]]:
        """Hidden states (time, hidden) of one direction over vectors (time, width) in its reading order, going on from ``last``, and its last state and cell."""
        h, u = self.hidden, self.p["u"][way]
        inner = x @ self.p["x"][way] + self.p["b"][way]
        state, cell = last or (np.zeros(h, np.float32), np.zeros(h, np.float32))
        out = np.empty((len(x), h), np.float32)
        for k in range(len(x)):
            a = inner[k] + state @ u
            gates = sigmoid(a[: 3 * h])
            cell = gates[h : 2 * h] * cell + gates[:h] * np.tanh(a[3 * h :])
            state = gates[2 * h :] * np.tanh(cell)
            out[k] = state
        return out, (state, cell)

    def logits(self, x: np.ndarray, mask: np.ndarray, keep: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
        states = self._run(x, mask, keep)
        return states[:, 0] @ self.p["o"][0] + states[::-1, 1] @ self.p["o"][1] + x @ self.p["s"] + self.p["c"], states

    def gradients(self, x: np.ndarray, mask: np.ndarray, target: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        t, b, h, p = *x.shape[:2], self.hidden, self.p
        keep: dict = {}
        y, states = self.logits(x, mask, keep)
        prob = sigmoid(y)
        n = max(1.0, float(mask.sum()))
        loss = float((-(target * np.log(prob + 1e-7) + (1 - target) * np.log(1 - prob + 1e-7)) * mask).sum() / n)
        d = ((prob - target) * mask / n).astype(np.float32)
        back = d[::-1]
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["c"][0] = d.sum()
        g["s"] = d.reshape(-1) @ x.reshape(t * b, -1)
        g["o"][0], g["o"][1] = np.einsum("tb,tbh->h", d, states[:, 0]), np.einsum("tb,tbh->h", back, states[:, 1])
        i, f, o, cand = (keep["inner"][..., j * h : (j + 1) * h] for j in range(4))
        live, tops = keep["live"], keep["tops"]
        # What a step multiplies its errors with, for all steps at once: the inputs of the gates and of the candidate, zero where the mask is.
        of_cell = np.stack([cand * i * (1 - i), keep["cells"] * f * (1 - f), np.zeros_like(o), i * (1 - cand * cand)], axis=3) * live[..., None]
        of_state, through = tops * o * (1 - o) * live, o * (1 - tops * tops) * live
        kept, passed = (~live).astype(np.float32), np.where(live, f, 1)
        errors = np.stack([d, back], axis=1)[..., None] * p["o"][:, None]
        turned = np.ascontiguousarray(p["u"].transpose(0, 2, 1))
        da = np.empty((t, 2, b, 4, h), np.float32)
        dh, dc = np.zeros((2, b, h), np.float32), np.zeros((2, b, h), np.float32)
        for k in range(t - 1, -1, -1):
            dh += errors[k]
            dc += dh * through[k]  # the error of the cell after the step
            now = da[k]
            np.multiply(dc[:, :, None], of_cell[k], out=now)
            now[:, :, 2] = dh * of_state[k]
            dh *= kept[k]
            dh += np.matmul(now.reshape(2, b, 4 * h), turned)
            dc *= passed[k]
        da = da.reshape(t, 2, b, 4 * h)
        before = np.concatenate([np.zeros((1, 2, b, h), np.float32), states[:-1]])
        for way, seen in ((0, x), (1, x[::-1])):
            own = da[:, way].reshape(t * b, 4 * h)
            g["x"][way] = seen.reshape(t * b, -1).T @ own
            g["u"][way] = before[:, way].reshape(t * b, h).T @ own
            g["b"][way, 0] = own.sum(axis=0)
        return loss, g
