"""A character-level bidirectional LSTM with CRF transitions, in numpy: training by backpropagation, Viterbi decoding."""

from __future__ import annotations

import numpy as np

#: Character classes: 0 padding, 1-95 printable ASCII, then white space, letters beyond ASCII, anything else.
N_CHARS = 99


def encode(text: str) -> np.ndarray:
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    out = np.where((code >= 32) & (code < 127), code - 31, np.where(code < 32, 96, np.where(code < 0x2000, 97, 98)))
    return out


def _sigmoid(z):
    return 1 / (1 + np.exp(-z))


class Tagger:
    def __init__(self, tags: int, embed: int = 10, hidden: int = 16, seed: int = 3):
        rng, f = np.random.default_rng(seed), np.float32
        self.h, self.tags = hidden, tags
        self.p = {"E": rng.normal(0, 0.3, (N_CHARS, embed)).astype(f), "W": rng.normal(0, 0.3, (2 * hidden, tags)).astype(f), "b": np.zeros(tags, f), "T": np.zeros((tags, tags), f), "S": np.zeros(tags, f)}
        for d in "fr":
            self.p[f"U{d}"] = rng.normal(0, 0.25, (embed + hidden, 4 * hidden)).astype(f)
            bias = np.zeros(4 * hidden, f)
            bias[hidden : 2 * hidden] = 1
            self.p[f"c{d}"] = bias

    def _run(self, x: np.ndarray, mask: np.ndarray, d: str, keep: list | None):
        """Hidden states of one direction over (B, L, embed)."""
        n, length, _ = x.shape
        h = c = np.zeros((n, self.h), np.float32)
        out = np.zeros((n, length, self.h), np.float32)
        u, bias, k = self.p[f"U{d}"], self.p[f"c{d}"], self.h
        for t in range(length) if d == "f" else range(length - 1, -1, -1):
            z_in = np.concatenate([x[:, t], h], axis=1)
            z = z_in @ u + bias
            i, f, o, g = _sigmoid(z[:, :k]), _sigmoid(z[:, k : 2 * k]), _sigmoid(z[:, 2 * k : 3 * k]), np.tanh(z[:, 3 * k :])
            m = mask[:, t : t + 1]
            c_new = f * c + i * g
            tc = np.tanh(c_new)
            if keep is not None:
                keep.append((t, z_in, i, f, o, g, c, tc, m))
            h, c = m * (o * tc) + (1 - m) * h, m * c_new + (1 - m) * c
            out[:, t] = h
        return out

    def emissions(self, ids: np.ndarray, mask: np.ndarray, keep: dict | None = None) -> np.ndarray:
        x = self.p["E"][ids]
        states = []
        for d in "fr":
            log = [] if keep is not None else None
            states.append(self._run(x, mask, d, log))
            if keep is not None:
                keep[d] = log
        both = np.concatenate(states, axis=2)
        if keep is not None:
            keep["both"] = both
        return both @ self.p["W"] + self.p["b"]

    def step(self, ids: np.ndarray, mask: np.ndarray, y: np.ndarray, state: dict, rate: float) -> float:
        """One Adam step on a batch (B, L); returns the mean negative log-likelihood of the tag sequences."""
        keep: dict = {}
        e = self.emissions(ids, mask, keep).astype(np.float64)
        n, length, k = e.shape
        tr, st = self.p["T"].astype(np.float64), self.p["S"].astype(np.float64)
        alpha = np.zeros((length, n, k))
        alpha[0] = st + e[:, 0]
        lse = lambda a, axis: (m := a.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(a - m).sum(axis=axis))
        for t in range(1, length):
            nxt = lse(alpha[t - 1][:, :, None] + tr[None], 1) + e[:, t]
            alpha[t] = np.where(mask[:, t, None] > 0, nxt, alpha[t - 1])
        beta = np.zeros((length, n, k))
        for t in range(length - 2, -1, -1):
            nxt = lse(tr[None] + (e[:, t + 1] + beta[t + 1])[:, None, :], 2)
            beta[t] = np.where(mask[:, t + 1, None] > 0, nxt, beta[t + 1])
        logz = lse(alpha[-1], 1)
        marg = np.exp(alpha + beta - logz[None, :, None]).transpose(1, 0, 2) * mask[:, :, None]
        gold = np.eye(k)[y] * mask[:, :, None]
        de = (marg - gold) / n
        g = {name: np.zeros_like(v, dtype=np.float64) for name, v in self.p.items()}
        score = (e * gold).sum() + (st * gold[:, 0]).sum()
        for t in range(1, length):
            m = mask[:, t]
            pair = np.exp(alpha[t - 1][:, :, None] + tr[None] + (e[:, t] + beta[t])[:, None, :] - logz[:, None, None]) * m[:, None, None]
            g["T"] += pair.sum(0) / n
            np.add.at(g["T"], (y[:, t - 1], y[:, t]), -m / n)
            score += (tr[y[:, t - 1], y[:, t]] * m).sum()
        g["S"] = (marg[:, 0] - gold[:, 0]).sum(0) / n
        both = keep["both"]
        g["W"] = both.reshape(-1, both.shape[2]).T @ de.reshape(-1, k)
        g["b"] = de.sum((0, 1))
        dboth = de @ self.p["W"].T
        dx = np.zeros((*ids.shape, self.p["E"].shape[1]))
        for j, d in enumerate("fr"):
            dh_all = dboth[:, :, j * self.h : (j + 1) * self.h]
            dh = dc = np.zeros((n, self.h))
            u = self.p[f"U{d}"]
            for t, z_in, i, f, o, gg, c_old, tc, m in reversed(keep[d]):
                dh = dh + dh_all[:, t]
                dht = m * dh
                dct = m * dc + dht * o * (1 - tc * tc)
                dz = np.concatenate([dct * gg * i * (1 - i), dct * c_old * f * (1 - f), dht * tc * o * (1 - o), dct * i * (1 - gg * gg)], axis=1)
                g[f"U{d}"] += z_in.T @ dz
                g[f"c{d}"] += dz.sum(0)
                din = dz @ u.T
                dx[:, t] += din[:, : dx.shape[2]]
                dh = din[:, dx.shape[2] :] + (1 - m) * dh
                dc = dct * f + (1 - m) * dc
        np.add.at(g["E"], ids, dx)
        norm = np.sqrt(sum(float((v * v).sum()) for v in g.values()))
        state["t"] = state.get("t", 0) + 1
        for name, v in g.items():
            v = v * min(1.0, 5.0 / max(norm, 1e-9))
            m1 = state[name, 1] = 0.9 * state.get((name, 1), 0) + 0.1 * v
            m2 = state[name, 2] = 0.99 * state.get((name, 2), 0) + 0.01 * v * v
            self.p[name] = (self.p[name] - rate * (m1 / (1 - 0.9 ** state["t"])) / (np.sqrt(m2 / (1 - 0.99 ** state["t"])) + 1e-8)).astype(np.float32)
        return float((logz.sum() - score) / n)

    def save(self, path) -> None:
        np.savez_compressed(path, **self.p)

    @classmethod
    def load(cls, file, tags: int) -> Tagger:
        out = cls(tags)
        with np.load(file, allow_pickle=False) as stored:
            out.p = {k: stored[k] for k in stored.files}
        out.h = out.p["Uf"].shape[1] // 4
        return out

    def decode(self, e: np.ndarray) -> np.ndarray:
        """The best tag sequence of one stretch of emissions (L, tags)."""
        d = Decoder(self)
        return np.array([*d.push(e), *d.end()], np.int64)


class Decoder:
    """Viterbi over emissions that come block by block. Tags are given out as soon as all surviving paths share them, so
    that memory does not grow with the stretch."""

    #: Steps between two looks for what all paths share.
    LOOK = 2048

    def __init__(self, model: Tagger):
        self.step, self.best, self.start = model.p["T"], None, model.p["S"]
        self.look = self.LOOK
        self.back: list[np.ndarray] = []  # back[i][tag]: the tag before, for each step that is not given out but the first

    def push(self, e: np.ndarray) -> list[int]:
        rows, at = [], 0
        if self.best is None and len(e):
            self.best, at = self.start + e[0], 1
        for t in range(at, len(e)):
            paths = self.best[:, None] + self.step
            rows.append(paths.argmax(0))
            self.best = paths.max(0) + e[t]
        self.back += rows
        return self._shared() if len(self.back) >= self.look else []

    def _shared(self) -> list[int]:
        """The tags before the last step at which all paths meet."""
        states = np.arange(len(self.best))
        for i in range(len(self.back) - 1, -1, -1):
            states = self.back[i][states]
            if (states == states[0]).all():
                out = self._trace(int(states[0]), i)
                self.back = self.back[i:]
                break
        else:
            out = []
        self.look = max(self.LOOK, 2 * len(self.back))
        return out

    def _trace(self, tag: int, n: int) -> list[int]:
        """Tags of the n steps before the one with this tag."""
        out = []
        for i in range(n - 1, -1, -1):
            tag = int(self.back[i][tag])
            out.append(tag)
        return out[::-1]

    def end(self) -> list[int]:
        if self.best is None:
            return []
        last = int(self.best.argmax())
        return [*self._trace(last, len(self.back)), last]
