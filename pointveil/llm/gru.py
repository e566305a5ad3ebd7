"""Gated recurrent layer in numpy: one time loop over a batch, with backpropagation through the window.

Gates and candidate use the softsign x / (1 + |x|), shifted and scaled to (0, 1) for gates.
"""

from __future__ import annotations

import numpy as np

F32 = np.float32


class Gru:
    """Recurrent weights of one direction; inputs come already projected to three gates."""

    def __init__(self, hidden: int, rng: np.random.Generator | None = None, u: np.ndarray | None = None):
        self.h = hidden
        self.u = u if u is not None else (rng.standard_normal((hidden, 3 * hidden)) * 0.5 / np.sqrt(hidden)).astype(F32)

    def step(self, x: np.ndarray, h: np.ndarray) -> np.ndarray:
        """The next state of every row."""
        n = self.h
        a = h @ self.u
        g = a[:, : 2 * n]
        g += x[:, : 2 * n]
        d = np.abs(g)
        d += 1
        g /= d
        g *= F32(0.5)
        g += F32(0.5)
        c = g[:, n:] * a[:, 2 * n :]
        c += x[:, 2 * n :]
        d = np.abs(c)
        d += 1
        c /= d
        h = h - c
        h *= g[:, :n]
        h += c
        return h

    def forward(self, x: np.ndarray, h: np.ndarray, keep: np.ndarray | None = None) -> tuple[np.ndarray, list]:
        """States (time, rows, hidden) for inputs (time, rows, 3 hidden), and what the way back needs.

        ``keep`` (time, rows, 1) is 0 where the state is cleared before the step.
        """
        n, out, tape = self.h, np.empty((*x.shape[:2], self.h), dtype=F32), []
        for t in range(len(x)):
            if keep is not None:
                h = h * keep[t]
            a = h @ self.u
            s = a[:, : 2 * n]
            s += x[t, :, : 2 * n]
            d = np.abs(s)
            d += 1
            s /= d
            g = s * F32(0.5)
            g += F32(0.5)
            c = g[:, n:] * a[:, 2 * n :]
            c += x[t, :, 2 * n :]
            d = np.abs(c)
            d += 1
            c /= d
            new = h - c
            new *= g[:, :n]
            new += c
            tape.append((h, a, g, c))
            out[t] = h = new
        return out, tape

    def backward(self, tape: list, d_out: np.ndarray, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Gradients of the inputs and of the recurrent weights; d_out holds the loss's gradient at each state."""
        n, steps = self.h, len(tape)
        dx = np.empty((steps, d_out.shape[1], 3 * n), dtype=F32)
        da = np.empty((steps, d_out.shape[1], 3 * n), dtype=F32)
        back = np.ascontiguousarray(self.u.T)
        dh = np.zeros_like(d_out[0])
        for t in range(steps - 1, -1, -1):
            h, a, g, c = tape[t]
            s, now, back_now = a[:, : 2 * n], dx[t], da[t]
            dh += d_out[t]
            z, r = g[:, :n], g[:, n:]
            # the softsign's slope is (1 - |value|) squared; a gate has half of it
            slope = np.abs(c)
            np.subtract(1, slope, out=slope)
            slope *= slope
            dc = now[:, 2 * n :]
            np.subtract(1, z, out=dc)
            dc *= dh
            dc *= slope
            slope = np.abs(s)
            np.subtract(1, slope, out=slope)
            slope *= slope
            slope *= F32(0.5)
            np.subtract(h, c, out=now[:, :n])
            now[:, :n] *= dh
            np.multiply(dc, a[:, 2 * n :], out=now[:, n : 2 * n])
            now[:, : 2 * n] *= slope
            back_now[:, : 2 * n] = now[:, : 2 * n]
            np.multiply(dc, r, out=back_now[:, 2 * n :])
            dh *= z
            dh += back_now @ back
            if keep is not None:
                dh *= keep[t]
        du = np.concatenate([h for h, *_ in tape]).T @ da.reshape(-1, 3 * n)
        return dx, du


class Adam:
    """Adam over a dict of arrays, updated in place."""

    def __init__(self, weights: dict[str, np.ndarray], rate: float):
        self.w, self.rate, self.t = weights, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in weights.items()}
        self.v = {k: np.zeros_like(v) for k, v in weights.items()}

    def apply(self, grads: dict[str, np.ndarray], clip: float = 5.0) -> None:
        self.t += 1
        norm = np.sqrt(sum(float((g * g).sum()) for g in grads.values()))
        scale = min(1.0, clip / (norm + 1e-9))
        rate = self.rate * np.sqrt(1 - 0.999**self.t) / (1 - 0.9**self.t)
        for k, g in grads.items():
            g = g * F32(scale)
            self.m[k] += F32(0.1) * (g - self.m[k])
            self.v[k] += F32(0.001) * (g * g - self.v[k])
            self.w[k] -= F32(rate) * self.m[k] / (np.sqrt(self.v[k]) + F32(1e-8))
