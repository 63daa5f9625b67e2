"""Language identification by a bidirectional gated recurrent network over bytes.

A text is read as byte windows: its words, with a blank on either side, long words in pieces of up to 30 bytes.
The network labels every byte position of a window; a document's probabilities pool the positions of its whole
text. Training is backpropagation through time in numpy, on the driver, over a bounded sample of documents;
prediction is one map-only pass in which a worker remembers the windows it has labelled already.

Defined results: a null text, or one without any letter, is ``und`` with score 0; with no training text every
document is ``und``; a text of one repeated word is pooled like any other; repeated rows are predicted each; other
columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_fold, slices

PIECE = 30
UNDETERMINED = "und"


def windows(text: str) -> list[bytes]:
    """The whole text as byte windows: words cut on white space, words over 30 bytes in pieces."""
    words = text.lower().encode().split()
    if max(map(len, words), default=0) <= PIECE:
        return words
    return [w[i : i + PIECE] for w in words for i in range(0, len(w), PIECE)]


def _pack(pieces: list[bytes]) -> np.ndarray:
    """Equal-length windows as a (time, window) array, a blank before and after."""
    return np.frombuffer(b"".join(b" " + p + b" " for p in pieces), dtype=np.uint8).reshape(len(pieces), -1).T


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-x))


@dataclass
class ByteGru:
    """Forward and backward gated units over bytes, with one softmax readout per position."""

    langs: list[str]
    p: dict[str, np.ndarray]

    @staticmethod
    def new(langs: list[str], hidden: int = 16, seed: int = 5) -> ByteGru:
        rng = np.random.default_rng(seed)
        p = {}
        for d in "fb":
            p[f"x{d}"] = rng.normal(0, 0.3, (256, 3 * hidden)).astype(np.float32)  # input weights, one row a byte; update, reset, candidate
            p[f"h{d}"] = rng.normal(0, 0.3 / np.sqrt(hidden), (hidden, 3 * hidden)).astype(np.float32)
            p[f"o{d}"] = rng.normal(0, 0.3, (hidden, len(langs))).astype(np.float32)
        p["bias"] = np.zeros(len(langs), dtype=np.float32)
        return ByteGru(langs, p)

    def _states(self, x: np.ndarray, d: str) -> tuple[np.ndarray, list[tuple]]:
        xw, hw = self.p[f"x{d}"], self.p[f"h{d}"]
        n = hw.shape[0]
        h = np.zeros((x.shape[1], n), dtype=np.float32)
        states, tape = [], []
        for row in x:
            a, b = xw[row], h @ hw
            z, r = _sigmoid(a[:, :n] + b[:, :n]), _sigmoid(a[:, n : 2 * n] + b[:, n : 2 * n])
            c = np.tanh(a[:, 2 * n :] + r * b[:, 2 * n :])
            tape.append((row, h, z, r, c, b[:, 2 * n :]))
            h = (1 - z) * h + z * c
            states.append(h)
        return np.stack(states), tape

    def positions(self, x: np.ndarray) -> np.ndarray:
        """Label probabilities of every position: (time, window, language)."""
        return self._forward(x)[0]

    def _forward(self, x: np.ndarray):
        f, tape_f = self._states(x, "f")
        b, tape_b = self._states(x[::-1], "b")
        logits = f @ self.p["of"] + b[::-1] @ self.p["ob"] + self.p["bias"]
        e = np.exp(logits - logits.max(axis=2, keepdims=True))
        return e / e.sum(axis=2, keepdims=True), f, b, tape_f, tape_b

    def gradients(self, x: np.ndarray, label: np.ndarray, weight: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Weighted cross entropy of all positions and its gradients, by backpropagation through time."""
        prob, f, b, tape_f, tape_b = self._forward(x)
        total = float(weight.sum()) * x.shape[0]
        picked = np.take_along_axis(prob, np.broadcast_to(label[None, :, None], (*x.shape, 1)), axis=2)[..., 0]
        loss = float(-(np.log(picked + 1e-12) * weight).sum() / total)
        delta = prob.copy()
        delta[:, np.arange(x.shape[1]), label] -= 1.0
        delta *= (weight / total)[None, :, None].astype(np.float32)
        g = {"bias": delta.sum(axis=(0, 1))}
        for d, states, tape, out in (("f", f, tape_f, delta), ("b", b, tape_b, delta[::-1])):
            hw = self.p[f"h{d}"]
            n = hw.shape[0]
            g[f"o{d}"] = np.einsum("tbn,tbk->nk", states, out)
            gx, gh = np.zeros_like(self.p[f"x{d}"]), np.zeros_like(hw)
            dh = np.zeros_like(states[0])
            back = out @ self.p[f"o{d}"].T
            for t in range(len(tape) - 1, -1, -1):
                row, before, z, r, c, inner = tape[t]
                dh = dh + back[t]
                dc = dh * z * (1 - c * c)
                dz = dh * (c - before) * z * (1 - z)
                dr = dc * inner * r * (1 - r)
                da = np.concatenate([dz, dr, dc], axis=1)
                db = np.concatenate([dz, dr, dc * r], axis=1)
                np.add.at(gx, row, da)
                gh += before.T @ db
                dh = dh * (1 - z) + db @ hw.T
            g[f"x{d}"], g[f"h{d}"] = gx, gh
        return loss, g


def train(samples: list[tuple[bytes, int, float]], langs: list[str], steps: int = 500, batch: int = 512, rate: float = 0.01, hidden: int = 16, seed: int = 5) -> ByteGru:
    """Adam over batches of equal-length windows; a sample is (window, language index, weight)."""
    model, rng = ByteGru.new(langs, hidden, seed), np.random.default_rng(seed)
    groups: dict[int, list[tuple[bytes, int, float]]] = {}
    for s in samples:
        groups.setdefault(len(s[0]), []).append(s)
    lengths = sorted(groups)
    share = np.array([sum(s[2] for s in groups[k]) for k in lengths], dtype=float)
    share /= share.sum()
    chance = {k: np.cumsum([s[2] for s in groups[k]]) for k in lengths}
    m = {k: np.zeros_like(v) for k, v in model.p.items()}
    v2 = {k: np.zeros_like(v) for k, v in model.p.items()}
    for step in range(1, steps + 1):
        k = lengths[rng.choice(len(lengths), p=share)]
        at = np.searchsorted(chance[k], rng.random(batch) * chance[k][-1])
        chosen = [groups[k][i] for i in at.tolist()]
        _, g = model.gradients(_pack([s[0] for s in chosen]), np.array([s[1] for s in chosen]), np.ones(batch))
        norm = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
        scale = min(1.0, 1.0 / (norm + 1e-9))
        lr = rate * min(1.0, 2.0 * (1 - step / (steps + 1)))
        for name, x in g.items():
            x = x * scale
            m[name] = 0.9 * m[name] + 0.1 * x
            v2[name] = 0.999 * v2[name] + 0.001 * x * x
            model.p[name] -= (lr * (m[name] / (1 - 0.9**step)) / (np.sqrt(v2[name] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return model


class Labeller:
    """Labels windows with a trained network and remembers them, up to ``most`` windows."""

    def __init__(self, model: ByteGru, most: int = 400_000) -> None:
        self.model, self.most = model, most
        self.index: dict[bytes, int] = {}
        self.table = np.zeros((1024, len(model.langs) + 1), dtype=np.float64)

    def learn(self, pieces: list[bytes]) -> None:
        if len(self.index) + len(pieces) > self.most:
            self.index = {}
        by_length: dict[int, list[bytes]] = {}
        for p in pieces:
            by_length.setdefault(len(p), []).append(p)
        for same in by_length.values():
            for i in range(0, len(same), 4096):
                part = same[i : i + 4096]
                prob = self.model.positions(_pack(part))
                at, n = len(self.index), len(part)
                while at + n > len(self.table):
                    self.table = np.concatenate([self.table, np.zeros_like(self.table)])
                self.table[at : at + n, :-1] = np.log(prob + 1e-9).sum(axis=0)
                self.table[at : at + n, -1] = prob.shape[0]
                self.index.update(zip(part, range(at, at + n), strict=True))

    def documents(self, texts: list[str | None]) -> list[tuple[str, float]]:
        """(language, probability) of every text, pooling the log probabilities of all its positions."""
        rows = [windows(t) if t and any(map(str.isalpha, t)) else [] for t in texts]
        seen = set().union(*rows)
        new = [p for p in seen if p not in self.index]
        if len(self.index) + len(new) > self.most:
            self.index, new = {}, list(seen)
        self.learn(new)
        out, get = [], self.index.__getitem__
        for row in rows:
            if not row:
                out.append((UNDETERMINED, 0.0))
                continue
            total = self.table[np.fromiter(map(get, row), dtype=np.int64, count=len(row))].sum(axis=0)
            pooled = total[:-1] / total[-1] * min(total[-1], 24.0)  # a product of experts over at most 24 independent positions
            e = np.exp(pooled - pooled.max())
            k = int(pooled.argmax())
            out.append((self.model.langs[k], float(e[k] / e.sum())))
        return out


def fit(docs: DataFrame, per_lang: int = 300, modulus: int = 5, held: int = 0) -> ByteGru | None:
    """Train on at most about ``per_lang`` documents of each language, drawn by hash from outside the held-out fold."""
    usable = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    usable = usable.where(~in_fold("doc_id", modulus, held) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    counts = {r.lang: r.n for r in usable.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return None
    rate = F.lit(0.0)
    for lang, n in counts.items():
        rate = F.when(F.col("lang") == lang, min(1.0, per_lang / n)).otherwise(rate)
    drawn = F.pmod(F.xxhash64(F.lit(11), "doc_id"), F.lit(1 << 30)) < rate * F.lit(float(1 << 30))
    rows = usable.where(drawn).select("lang", "text").collect()
    langs = sorted(counts)
    seen = {lang: Counter() for lang in langs}
    for r in rows:
        if any(map(str.isalpha, r.text)):
            seen[r.lang].update(set(windows(r.text)))
    samples = [(w, langs.index(lang), n / sum(c.values())) for lang, c in sorted(seen.items()) for w, n in sorted(c.items())]
    return train(samples, langs) if samples else None


def identify(docs: DataFrame, model: ByteGru | None, modulus: int = 5, held: int = 0, batch_bytes: int = 4 << 20) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score. Predictions read the text alone."""

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labeller = Labeller(model) if model else None
        for batch in slices(batches, "text", batch_bytes):
            texts = batch.column("text").to_pylist()
            found = labeller.documents(texts) if labeller else [(UNDETERMINED, 0.0)] * len(texts)
            yield pa.record_batch([batch.column("doc_id"), batch.column("held_out"), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), in_fold("doc_id", modulus, held).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(label, "doc_id long, held_out boolean, lang_pred string, score double")
