"""A character-level bidirectional LSTM with CRF transitions, trained and run in numpy."""

from __future__ import annotations

import re

import numpy as np

#: Classes of characters the model sees; letters, digits and blanks are pooled, signs stand alone.
SIGNS = "@.+-_%()/:,;#=\n"
KINDS = ("email", "ip", "card", "phone")
#: What the tagger marks beside the kinds that patterns find.
MORE_KINDS = ("secret",)
TAGS = ("O", *(f"{p}-{k}" for k in KINDS + MORE_KINDS for p in "BI"))
N_CLASS = 5 + len(SIGNS)


def _classes() -> np.ndarray:
    t = np.full(128, 4, np.int64)
    for c in range(128):
        ch = chr(c)
        t[c] = 0 if ch.isdigit() else 1 if ch.islower() else 2 if ch.isupper() else 3 if ch.isspace() and ch != "\n" else 5 + SIGNS.index(ch) if ch in SIGNS else 4
    return t


_TABLE = _classes()


def classes_of(text: str) -> np.ndarray:
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    return np.where(code < 128, _TABLE[np.minimum(code, 127)], 1)


def allowed() -> np.ndarray:
    """0 where a tag may follow another, else very low: I-x only after B-x or I-x."""
    a = np.zeros((len(TAGS), len(TAGS)))
    for i, x in enumerate(TAGS):
        for j, y in enumerate(TAGS):
            if y[0] == "I" and x[1:] != y[1:]:
                a[i, j] = -1e4
    return a


FORBID = allowed()
NO_START = np.array([-1e4 if t[0] == "I" else 0.0 for t in TAGS])


def _sigmoid(x):
    return 0.5 * (np.tanh(0.5 * x) + 1)


def _logsumexp(x, axis):
    m = x.max(axis=axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis=axis, keepdims=True))).squeeze(axis)


class Tagger:
    def __init__(self, hidden: int = 12, seed: int = 7):
        r = np.random.default_rng(seed)
        self.hidden = h = hidden
        self.p: dict[str, np.ndarray] = {}
        for d in "fb":
            self.p["x" + d] = r.normal(0, 0.3, (N_CLASS, 4 * h))
            self.p["h" + d] = r.normal(0, 0.3, (h, 4 * h))
            self.p["c" + d] = np.concatenate((np.zeros(h), np.ones(h), np.zeros(2 * h)))
        self.p["out"] = r.normal(0, 0.3, (2 * h, len(TAGS)))
        self.p["bias"] = np.zeros(len(TAGS))
        self.p["move"] = np.zeros((len(TAGS), len(TAGS)))

    def _direction(self, x: np.ndarray, d: str, keep: bool):
        """x: (n, time) classes. Hidden states (time, n, hidden), and what backpropagation needs."""
        n, steps = x.shape
        h, hid = np.zeros((n, self.hidden)), self.hidden
        c = np.zeros_like(h)
        wx, wh, b = self.p["x" + d], self.p["h" + d], self.p["c" + d]
        out, trail = np.empty((steps, n, hid)), []
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            z = wx[x[:, t]] + h @ wh + b
            s = _sigmoid(z[:, : 3 * hid])
            g = np.tanh(z[:, 3 * hid :])
            i, f, o = s[:, :hid], s[:, hid : 2 * hid], s[:, 2 * hid :]
            new = f * c + i * g
            tc = np.tanh(new)
            if keep:
                trail.append((t, h, c, i, f, o, g, tc))
            h, c = o * tc, new
            out[t] = h
        return out, trail

    def emissions(self, x: np.ndarray, keep: bool = False):
        f, tf = self._direction(x, "f", keep)
        b, tb = self._direction(x, "b", keep)
        both = np.concatenate((f, b), axis=2)
        return both @ self.p["out"] + self.p["bias"], both, tf, tb

    def loss_and_gradient(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        e, both, tf, tb = self.emissions(x, keep=True)
        steps, n, k = e.shape
        move = self.p["move"] + FORBID
        alpha, beta = np.empty_like(e), np.zeros_like(e)
        alpha[0] = e[0] + NO_START
        for t in range(1, steps):
            alpha[t] = _logsumexp(alpha[t - 1][:, :, None] + move, 1) + e[t]
        for t in range(steps - 2, -1, -1):
            beta[t] = _logsumexp(move[None] + (e[t + 1] + beta[t + 1])[:, None, :], 2)
        z = _logsumexp(alpha[-1], 1)
        grad_e = np.exp(alpha + beta - z[None, :, None])
        grad_move = np.zeros((k, k))
        for t in range(1, steps):
            grad_move += np.exp(alpha[t - 1][:, :, None] + move + (e[t] + beta[t])[:, None, :] - z[:, None, None]).sum(0)
        rows = np.arange(n)
        gold = NO_START[y[:, 0]] + e[0, rows, y[:, 0]]
        grad_e[0, rows, y[:, 0]] -= 1
        for t in range(1, steps):
            gold = gold + move[y[:, t - 1], y[:, t]] + e[t, rows, y[:, t]]
            grad_e[t, rows, y[:, t]] -= 1
            np.subtract.at(grad_move, (y[:, t - 1], y[:, t]), 1)
        grad = {"move": grad_move / n, "bias": grad_e.sum((0, 1)) / n, "out": np.einsum("tnh,tnk->hk", both, grad_e) / n}
        down = grad_e @ self.p["out"].T
        for d, trail, at in (("f", tf, 0), ("b", tb, self.hidden)):
            grad |= self._backward(x, d, trail, down[:, :, at : at + self.hidden], n)
        return float((z - gold).mean()), grad

    def _backward(self, x, d, trail, down, n):
        hid, wh = self.hidden, self.p["h" + d]
        gx, gh, gb = np.zeros_like(self.p["x" + d]), np.zeros_like(wh), np.zeros(4 * hid)
        dh, dc = np.zeros((n, hid)), np.zeros((n, hid))
        for t, h, c, i, f, o, g, tc in reversed(trail):
            dh = dh + down[t]
            dc = dc + dh * o * (1 - tc * tc)
            dz = np.concatenate((dc * g * i * (1 - i), dc * c * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - g * g)), axis=1)
            np.add.at(gx, x[:, t], dz)
            gh += h.T @ dz
            gb += dz.sum(0)
            dh, dc = dz @ wh.T, dc * f
        return {"x" + d: gx / n, "h" + d: gh / n, "c" + d: gb / n}

    def fit(self, x: np.ndarray, y: np.ndarray, steps: int = 220, batch: int = 48, rate: float = 0.02, seed: int = 7) -> list[float]:
        """Adam over random batches; the losses."""
        r = np.random.default_rng(seed)
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v2 = {k: np.zeros_like(v) for k, v in self.p.items()}
        losses = []
        for step in range(1, steps + 1):
            at = r.choice(len(x), size=min(batch, len(x)), replace=False)
            loss, grad = self.loss_and_gradient(x[at], y[at])
            losses.append(loss)
            pace = rate * min(1.0, 2 * (1 - step / (steps + 1)))
            for k, g in grad.items():
                g = np.clip(g, -1, 1)
                m[k] = 0.9 * m[k] + 0.1 * g
                v2[k] = 0.99 * v2[k] + 0.01 * g * g
                self.p[k] -= pace * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.99**step)) + 1e-8)
        return losses

    def decode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Best tags (n, time) and their emission margins over O."""
        e, *_ = self.emissions(x)
        steps, n, k = e.shape
        move = self.p["move"] + FORBID
        score, back = e[0] + NO_START, np.empty((steps, n, k), np.int8)
        for t in range(1, steps):
            ways = score[:, :, None] + move
            back[t] = ways.argmax(1)
            score = np.take_along_axis(ways, back[t][:, None, :].astype(np.int64), 1)[:, 0, :] + e[t]
        tags = np.empty((n, steps), np.int64)
        tags[:, -1] = score.argmax(1)
        for t in range(steps - 1, 0, -1):
            tags[:, t - 1] = back[t][np.arange(n), tags[:, t]]
        margin = np.take_along_axis(e, tags.T[:, :, None], 2)[:, :, 0].T - e[:, :, 0].T
        return tags, margin


def spans_of(tags: np.ndarray) -> list[tuple[str, int, int]]:
    out, start = [], -1
    for i, t in enumerate([*tags.tolist(), 0]):
        if start >= 0 and TAGS[t][0] != "I":
            out.append((TAGS[tags[start]][2:], start, i))
            start = -1
        if TAGS[t][0] == "B":
            start = i
    return out


TRIGGER = re.compile("[0-9@]+")
