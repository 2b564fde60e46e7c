"""A character-level bidirectional LSTM with CRF transitions, trained and run in numpy."""

from __future__ import annotations

import numpy as np

#: Input symbols: one per ASCII character with letters folded and digits merged, one for all else, one for padding.
PAD, OTHER = 0, 1


def symbols(text: np.ndarray) -> np.ndarray:
    """Code points → input symbols (0 is padding)."""
    out = np.full(text.shape, OTHER, np.int64)
    plain = text < 128
    out[plain] = text[plain] + 2
    upper = (text >= 65) & (text <= 90)
    out[upper] = text[upper] + 32 + 2
    digit = (text >= 48) & (text <= 57)
    out[digit] = 48 + 2
    return out


N_SYMBOLS = 130


def _sig(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Tagger:
    """Parameters are a dict of float32 arrays, so a model is pickled as it is."""

    def __init__(self, n_tags: int, embed: int = 12, hidden: int = 16, seed: int = 3):
        rng = np.random.default_rng(seed)
        draw = lambda *s: (rng.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        self.n_tags, self.hidden = n_tags, hidden
        self.p = {"E": draw(N_SYMBOLS, embed) * np.float32(np.sqrt(N_SYMBOLS) * 0.3), "T": np.zeros((n_tags, n_tags), np.float32), "S": np.zeros(n_tags, np.float32), "O": draw(2 * hidden, n_tags), "b": np.zeros(n_tags, np.float32)}
        for d in "fr":
            self.p["W" + d] = draw(embed + hidden, 4 * hidden)
            self.p["c" + d] = np.concatenate([np.zeros(hidden), np.ones(hidden), np.zeros(2 * hidden)]).astype(np.float32)

    def _lstm(self, x: np.ndarray, live: np.ndarray, d: str, keep: bool):
        """x: (T, N, E) in reading order of the direction. Padding keeps the state as it is."""
        steps, n, _ = x.shape
        h = c = np.zeros((n, self.hidden), np.float32)
        k, out, tape = self.hidden, np.empty((steps, n, self.hidden), np.float32), []
        for t in range(steps):
            z = np.concatenate([x[t], h], 1)
            a = z @ self.p["W" + d] + self.p["c" + d]
            i, f, o, g = _sig(a[:, :k]), _sig(a[:, k : 2 * k]), _sig(a[:, 2 * k : 3 * k]), np.tanh(a[:, 3 * k :])
            m = live[t][:, None]
            c2 = m * (f * c + i * g) + (1 - m) * c
            s = np.tanh(c2)
            h2 = m * (o * s) + (1 - m) * h
            if keep:
                tape.append((z, i, f, o, g, c, s, m))
            h, c = h2, c2
            out[t] = h
        return out, tape

    def _lstm_back(self, grad: np.ndarray, tape: list, d: str, into: dict) -> np.ndarray:
        k = self.hidden
        w = self.p["W" + d]
        embed = w.shape[0] - k
        dx = np.empty((*grad.shape[:2], embed), np.float32)
        dh = dc = np.zeros(grad.shape[1:], np.float32)
        for t in range(len(tape) - 1, -1, -1):
            z, i, f, o, g, c, s, m = tape[t]
            dh = dh + grad[t]
            through = dh * m
            dcell = dc + through * o * (1 - s * s)
            inner = dcell * m
            da = np.concatenate([inner * g * i * (1 - i), inner * c * f * (1 - f), through * s * o * (1 - o), inner * i * (1 - g * g)], 1)
            into["W" + d] += z.T @ da
            into["c" + d] += da.sum(0)
            dz = da @ w.T
            dx[t] = dz[:, :embed]
            dh = dz[:, embed:] + dh * (1 - m)
            dc = inner * f + dcell * (1 - m)
        return dx

    def emissions(self, x: np.ndarray, keep: bool = False):
        """Symbols (N, T) → tag scores (T, N, tags)."""
        live = (x.T != PAD).astype(np.float32)
        e = self.p["E"][x.T]
        forward, tf = self._lstm(e, live, "f", keep)
        back, tb = self._lstm(e[::-1], live[::-1], "r", keep)
        both = np.concatenate([forward, back[::-1]], 2)
        return both @ self.p["O"] + self.p["b"], (live, both, tf, tb)

    def loss_and_gradient(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
        """Mean negative log-likelihood of the tag rows ``y`` and its gradient. Texts start at column 0."""
        scores, (live, both, tf, tb) = self.emissions(x, keep=True)
        steps, n, k = scores.shape
        trans, start = self.p["T"], self.p["S"]
        alpha = np.empty((steps, n, k))
        alpha[0] = scores[0] + start
        for t in range(1, steps):
            q = alpha[t - 1][:, :, None] + trans[None]
            top = q.max(1)
            step = top + np.log(np.exp(q - top[:, None]).sum(1)) + scores[t]
            alpha[t] = np.where(live[t][:, None] > 0, step, alpha[t - 1])
        top = alpha[-1].max(1)
        log_z = top + np.log(np.exp(alpha[-1] - top[:, None]).sum(1))
        beta = np.zeros((steps, n, k))
        g = {name: np.zeros_like(v) for name, v in self.p.items()}
        for t in range(steps - 2, -1, -1):
            nxt = scores[t + 1] + beta[t + 1]
            q = trans[None] + nxt[:, None, :]
            top = q.max(2)
            step = top + np.log(np.exp(q - top[:, :, None]).sum(2))
            on = live[t + 1][:, None] > 0
            beta[t] = np.where(on, step, 0)
            pair = np.exp(alpha[t][:, :, None] + q - log_z[:, None, None]) * on[:, :, None]
            g["T"] += pair.sum(0).astype(np.float32)
        unary = np.exp(alpha + beta - log_z[None, :, None]) * live[:, :, None]
        rows, total = np.arange(n), 0.0
        first = y[:, 0]
        total += (scores[0][rows, first] + start[first]).sum()
        unary[0][rows, first] -= 1
        g["S"] += unary[0].sum(0).astype(np.float32)
        for t in range(1, steps):
            on = live[t] > 0
            r = rows[on]
            total += (scores[t][r, y[r, t]] + trans[y[r, t - 1], y[r, t]]).sum()
            unary[t][r, y[r, t]] -= 1
            np.add.at(g["T"], (y[r, t - 1], y[r, t]), -1)
        ds = unary.astype(np.float32)
        g["O"] += np.tensordot(both, ds, ([0, 1], [0, 1]))
        g["b"] += ds.sum((0, 1))
        dboth = ds @ self.p["O"].T
        h = self.hidden
        dx = self._lstm_back(dboth[:, :, :h], tf, "f", g) + self._lstm_back(dboth[::-1, :, h:], tb, "r", g)[::-1]
        np.add.at(g["E"], x.T, dx)
        return float((log_z.sum() - total) / n), {name: v / n for name, v in g.items()}

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 6, batch: int = 48, rate: float = 0.015, seed: int = 11) -> list[float]:
        """Adam over shuffled batches; returns the mean loss of each epoch."""
        rng, step, history = np.random.default_rng(seed), 0, []
        first = {k: np.zeros_like(v) for k, v in self.p.items()}
        second = {k: np.zeros_like(v) for k, v in self.p.items()}
        for _ in range(epochs):
            losses = []
            order = rng.permutation(len(x))
            for at in range(0, len(x), batch):
                pick = order[at : at + batch]
                loss, g = self.loss_and_gradient(x[pick], y[pick])
                losses.append(loss)
                step += 1
                for k, v in g.items():
                    v = np.clip(v, -5, 5)
                    first[k] = 0.9 * first[k] + 0.1 * v
                    second[k] = 0.99 * second[k] + 0.01 * v * v
                    self.p[k] = (self.p[k] - rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
            history.append(float(np.mean(losses)))
        return history

    def decode(self, x: np.ndarray) -> np.ndarray:
        """Best tag row of each window (Viterbi); padding gets tag 0."""
        scores, (live, *_) = self.emissions(x)
        steps, n, k = scores.shape
        best = scores[0] + self.p["S"]
        back = np.zeros((steps, n, k), np.int8)
        for t in range(1, steps):
            q = best[:, :, None] + self.p["T"][None]
            back[t] = q.argmax(1)
            moved = q.max(1) + scores[t]
            on = live[t][:, None] > 0
            back[t] = np.where(on, back[t], np.arange(k))
            best = np.where(on, moved, best)
        tags = np.zeros((n, steps), np.int64)
        tags[:, -1] = best.argmax(1)
        rows = np.arange(n)
        for t in range(steps - 1, 0, -1):
            tags[:, t - 1] = back[t][rows, tags[:, t]]
        return np.where(x == PAD, 0, tags)
