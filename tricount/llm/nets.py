"""Small pieces of trained networks in numpy: the Adam update, logistic calibration, a gated recurrent unit with its gradient."""

from __future__ import annotations

import numpy as np

Params = dict[str, np.ndarray]


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


class Adam:
    def __init__(self, params: Params, rate: float = 0.01) -> None:
        self.params, self.rate, self.turn = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: Params) -> None:
        self.turn += 1
        for k, g in grads.items():
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            self.params[k] -= self.rate * (self.m[k] / (1 - 0.9**self.turn)) / (np.sqrt(self.v[k] / (1 - 0.999**self.turn)) + 1e-8)


def platt(score: np.ndarray, y: np.ndarray, steps: int = 200) -> tuple[float, float]:
    """(slope, shift) of the logistic curve from scores to labels, by Newton steps with a small ridge."""
    mean, scale = float(score.mean()), float(score.std()) + 1e-6
    x = np.stack([(score - mean) / scale, np.ones(len(score))], axis=1)
    w = np.zeros(2)
    for _ in range(steps):
        p = sigmoid(x @ w)
        hess = x.T @ (x * (p * (1 - p) + 1e-6)[:, None]) + 1e-2 * np.eye(2)
        step = np.linalg.solve(hess, x.T @ (y - p) - 1e-2 * w)
        w += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    slope = max(w[0], 1e-3) / scale
    return slope, w[1] - slope * mean


def gru_params(rng: np.random.Generator, inputs: int, hidden: int, name: str) -> Params:
    draw = lambda *shape: (rng.standard_normal(shape) / np.sqrt(shape[0])).astype(np.float32)
    return {f"{name}.w": draw(inputs, 3 * hidden), f"{name}.u": draw(hidden, 3 * hidden), f"{name}.b": np.zeros(3 * hidden, dtype=np.float32)}


def gru(projected: np.ndarray, mask: np.ndarray, u: np.ndarray, keep: bool = False) -> tuple[np.ndarray, list]:
    """States (time, row, hidden) from projected inputs (time, row, 3 * hidden); where mask (time, row) is 0 the state stays. `keep` records what gru_grad() needs."""
    time, rows, width = projected.shape
    hidden = width // 3
    h = np.zeros((rows, hidden), dtype=np.float32)
    states, tape = np.empty((time, rows, hidden), dtype=np.float32), []
    for t in range(time):
        a, r_part = projected[t], h @ u
        gates = sigmoid(a[:, : 2 * hidden] + r_part[:, : 2 * hidden])
        z, r = gates[:, :hidden], gates[:, hidden:]
        n = np.tanh(a[:, 2 * hidden :] + r * r_part[:, 2 * hidden :])
        m = mask[t][:, None]
        new = h + m * (1 - z) * (n - h)
        if keep:
            tape.append((h, z, r, n, r_part[:, 2 * hidden :], m))
        h = new
        states[t] = h
    return states, tape


def gru_grad(d_states: np.ndarray, tape: list, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(gradient of the projected inputs, gradient of u) from that of the states."""
    time, rows, hidden = d_states.shape
    d_projected, d_u = np.zeros((time, rows, 3 * hidden), dtype=np.float32), np.zeros_like(u)
    dh = np.zeros((rows, hidden), dtype=np.float32)
    for t in range(time - 1, -1, -1):
        h, z, r, n, n_part, m = tape[t]
        dh = dh + d_states[t]
        dn = dh * m * (1 - z) * (1 - n * n)
        dz = dh * m * (h - n) * z * (1 - z)
        dr = dn * n_part * r * (1 - r)
        d_projected[t] = np.concatenate([dz, dr, dn], axis=1)
        through = np.concatenate([dz, dr, dn * r], axis=1)
        d_u += h.T @ through
        dh = dh * (1 - m * (1 - z)) + through @ u.T
    return d_projected, d_u
