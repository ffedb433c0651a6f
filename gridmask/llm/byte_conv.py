"""A small byte convolutional network in numpy, for the two learned text classifiers.

Bytes are embedded, filters of several widths run over them, each filter's largest response in a window is kept
(after a rectifier), and a dense layer maps these to hidden features. Windows have a fixed length and overlap by the
widest filter less one, so that every byte and every filter position of a text is covered. A document's features
are the largest and the mean of its windows' hidden features; a linear layer and a softmax give class probabilities.

The filters of all widths are one matrix over the widest span, with zeros where a filter is shorter, so that a
block of windows costs one matrix product.
"""

from __future__ import annotations

import numpy as np

PAD = 0


def cut(text: bytes, window: int, overlap: int) -> np.ndarray:
    """(n, window) bytes: windows that cover the whole text, the last one padded; one window for an empty text."""
    step = window - overlap
    n = max(1, -(-(len(text) - overlap) // step))
    padded = np.zeros(n * step + overlap, np.uint8)
    padded[: len(text)] = np.frombuffer(text, np.uint8)
    return np.lib.stride_tricks.as_strided(padded, (n, window), (step, 1))


class ByteConv:
    def __init__(self, classes: int, window: int = 256, widths: tuple[int, ...] = (2, 3, 4, 5), filters: int = 8, embed: int = 8, hidden: int = 16, seed: int = 1) -> None:
        rng = np.random.default_rng(seed)
        self.window, self.span, self.filters, self.embed = window, max(widths), filters * len(widths), embed
        f32 = lambda *shape, scale: (rng.standard_normal(shape) * scale).astype(np.float32)
        self.p = {
            "E": f32(256, embed, scale=0.5),
            "W": f32(self.span * embed, self.filters, scale=1 / np.sqrt(self.span * embed / 2)),
            "b": np.zeros(self.filters, np.float32),
            "H": f32(self.filters, hidden, scale=1 / np.sqrt(self.filters)),
            "h": np.zeros(hidden, np.float32),
            "O": f32(2 * hidden, classes, scale=0.1),
            "o": np.zeros(classes, np.float32),
        }
        self.mask = np.zeros((self.span, embed, self.filters), np.float32)
        for i, w in enumerate(widths):
            self.mask[:w, :, i * filters : (i + 1) * filters] = 1
        self.mask = self.mask.reshape(self.span * embed, self.filters)
        self.p["W"] *= self.mask

    @property
    def overlap(self) -> int:
        return self.span - 1

    def _columns(self, windows: np.ndarray) -> np.ndarray:
        """(n * positions, span * embed)."""
        e = self.p["E"][windows]
        n, positions = len(windows), self.window - self.span + 1
        s = e.strides
        view = np.lib.stride_tricks.as_strided(e, (n, positions, self.span * self.embed), (s[0], s[1], s[2]))
        return view.reshape(n * positions, -1)

    def pooled(self, windows: np.ndarray, block: int = 48) -> np.ndarray:
        """(n, filters): the largest rectified response of each filter in each window."""
        out = np.empty((len(windows), self.filters), np.float32)
        for at in range(0, len(windows), block):
            w = windows[at : at + block]
            r = self._columns(w) @ self.p["W"]
            out[at : at + block] = r.reshape(len(w), -1, self.filters).max(axis=1)
        return np.maximum(out + self.p["b"], 0)

    def hidden(self, windows: np.ndarray) -> np.ndarray:
        return np.maximum(self.pooled(windows) @ self.p["H"] + self.p["h"], 0)

    def documents(self, hidden: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """(documents, 2 * hidden): largest and mean over each document's windows."""
        counts = np.diff(starts, append=len(hidden))[:, None]
        return np.concatenate([np.maximum.reduceat(hidden, starts), np.add.reduceat(hidden, starts) / counts], axis=1)

    def scores(self, features: np.ndarray) -> np.ndarray:
        z = features @ self.p["O"] + self.p["o"]
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    def predict(self, texts: list[bytes], at_once: int = 2048) -> np.ndarray:
        """(texts, classes) probabilities over whole texts; a long text's windows go through in blocks."""
        out = np.empty((len(texts), self.p["o"].shape[0]), np.float64)
        held: list[np.ndarray] = []
        who: list[int] = []

        def flush() -> None:
            if held:
                starts = np.cumsum([0, *map(len, held[:-1])])
                out[who] = self.scores(self.documents(self.hidden(np.concatenate(held)), starts))
                held.clear()
                who.clear()

        size = 0
        for i, t in enumerate(texts):
            w = cut(t, self.window, self.overlap)
            if len(w) > at_once:
                most, total = None, 0.0
                for at in range(0, len(w), at_once):
                    h = self.hidden(w[at : at + at_once])
                    most = h.max(axis=0) if most is None else np.maximum(most, h.max(axis=0))
                    total = total + h.sum(axis=0)
                out[i] = self.scores(np.concatenate([most, total / len(w)])[None])[0]
                continue
            held.append(w)
            who.append(i)
            size += len(w)
            if size >= at_once:
                flush()
                size = 0
        flush()
        return out

    def fit(self, texts: list[bytes], labels: np.ndarray, weights: np.ndarray, epochs: int = 5, least_steps: int = 400, windows_per_text: int = 4, batch: int = 64, rate: float = 4e-3, seed: int = 2) -> float:
        """Adam on cross entropy; an epoch sees up to windows_per_text random windows of each text. Few texts are
        seen more often, for at least least_steps steps. Last epoch's loss."""
        rng = np.random.default_rng(seed)
        epochs = max(epochs, -(-least_steps // -(-len(texts) // batch)))
        all_windows = [cut(t, self.window, self.overlap) for t in texts]
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v2 = {k: np.zeros_like(v) for k, v in self.p.items()}
        step, loss, total_steps = 0, 0.0, epochs * -(-len(texts) // batch)
        for _ in range(epochs):
            loss = 0.0
            order = rng.permutation(len(texts))
            for at in range(0, len(order), batch):
                mine = order[at : at + batch]
                picked = [all_windows[i][np.sort(rng.choice(len(all_windows[i]), min(windows_per_text, len(all_windows[i])), replace=False))] for i in mine]
                starts = np.cumsum([0, *map(len, picked[:-1])])
                value, g = self._gradients(np.concatenate(picked), starts, labels[mine], weights[mine])
                loss += value * len(mine) / len(order)
                step += 1
                now = rate * min(1.0, 2 * (1 - step / (total_steps + 1)))
                for k, x in g.items():
                    m[k] = 0.9 * m[k] + 0.1 * x
                    v2[k] = 0.999 * v2[k] + 0.001 * x * x
                    self.p[k] -= (now * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
                self.p["W"] *= self.mask
        return loss

    def _gradients(self, windows: np.ndarray, starts: np.ndarray, labels: np.ndarray, weights: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        n, positions = len(windows), self.window - self.span + 1
        cols = self._columns(windows)
        r = (cols @ self.p["W"]).reshape(n, positions, self.filters)
        where = r.argmax(axis=1)
        top = np.take_along_axis(r, where[:, None], axis=1)[:, 0] + self.p["b"]
        pooled = np.maximum(top, 0)
        pre = pooled @ self.p["H"] + self.p["h"]
        hid = np.maximum(pre, 0)
        features = self.documents(hid, starts)
        prob = self.scores(features)
        d, w = len(starts), weights / weights.sum()
        loss = float(-(np.log(prob[np.arange(d), labels] + 1e-12) * w).sum())
        dz = prob.copy()
        dz[np.arange(d), labels] -= 1
        dz = (dz * w[:, None]).astype(np.float32)
        g = {"O": features.T @ dz, "o": dz.sum(axis=0)}
        df = dz @ self.p["O"].T
        k = hid.shape[1]
        counts = np.diff(starts, append=n)
        doc = np.repeat(np.arange(d), counts)
        dh = df[doc, k:] / counts[doc][:, None]
        is_top = hid == features[doc, :k]
        dh = dh + df[doc, :k] * is_top
        dh = dh * (pre > 0)
        g |= {"H": pooled.T @ dh, "h": dh.sum(axis=0)}
        dt = (dh @ self.p["H"].T) * (top > 0)
        g["b"] = dt.sum(axis=0)
        # only each filter's best position in each window passes a gradient on
        rows = (np.arange(n)[:, None] * positions + where).ravel()
        picked = cols[rows].reshape(n, self.filters, -1)
        g["W"] = np.einsum("nfc,nf->cf", picked, dt, optimize=True) * self.mask
        dcol = dt[:, :, None] * self.p["W"].T[None]
        byte = np.lib.stride_tricks.sliding_window_view(windows, self.span, axis=1)[np.arange(n)[:, None], where]
        ge = np.zeros((256, self.embed), np.float32)
        np.add.at(ge, byte.ravel(), dcol.reshape(-1, self.embed))
        g["E"] = ge
        return loss, g
