"""Language identification by a bidirectional gated recurrent network over bytes, in numpy.

The UTF-8 bytes of a text are cut into windows of WINDOW bytes; the network reads each window in both directions, gives
every position a distribution over the languages, and a document's distribution is the mean over all its positions.
Gates are piecewise linear, which halves the time of a step.  Training is backpropagation through time with Adam on a
bounded sample of labelled documents; prediction covers every byte of every text.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidy

WINDOW = 64
UNDETERMINED = "und"
_LETTER = re.compile(r"[^\W\d_]")


@dataclass(frozen=True)
class Training:
    """Bounds of the fit.  documents_per_language and windows_per_document bound the sample whatever the input's size."""

    hidden: int = 8
    documents_per_language: int = 400
    windows_per_document: int = 12
    steps: int = 500
    batch: int = 256
    rate: float = 0.02
    seed: int = 7


class ByteGru:
    """Parameters per direction: E (256 x 3H input rows, biases included), U (H x 2H gates), V (H x H candidate)."""

    def __init__(self, languages: list[str], hidden: int, seed: int = 0):
        rng, h = np.random.default_rng(seed), hidden
        f = lambda *shape, s=0.3: rng.normal(0, s, shape).astype(np.float32)
        self.languages, self.hidden = languages, hidden
        self.p = {f"{n}{d}": v for d in "fb" for n, v in (("E", f(257, 3 * h)), ("U", f(h, 2 * h)), ("V", f(h, h)))}
        self.p |= {"W": f(2 * h, len(languages)), "c": np.zeros(len(languages), np.float32)}

    def states(self, x: np.ndarray, d: str, keep: list | None = None) -> np.ndarray:
        """Hidden states (T, B, H) of windows x (T, B); direction b reads from the end.  keep collects what training needs."""
        h, (steps, b) = self.hidden, x.shape
        e, u, v = self.p["E" + d], self.p["U" + d], self.p["V" + d]
        out, s = np.empty((steps, b, h), np.float32), np.zeros((b, h), np.float32)
        gates = np.empty((b, 2 * h), np.float32)
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            row = e[x[t]]
            np.matmul(s, u, out=gates)
            gates += row[:, :2 * h]
            raw = gates.copy() if keep is not None else None
            gates *= np.float32(0.25)
            gates += np.float32(0.5)
            np.clip(gates, 0, 1, out=gates)
            z, r = gates[:, :h], gates[:, h:]
            c = r * s
            n = c @ v
            n += row[:, 2 * h:]
            np.tanh(n, out=n)
            if keep is not None:
                keep.append((t, s, raw, z.copy(), r.copy(), n.copy(), c))
            s = s + z * (n - s)
            out[t] = s
        return out

    def positions(self, x: np.ndarray) -> np.ndarray:
        """Probabilities (T, B, languages) at every position of the windows x (T, B)."""
        logits = np.concatenate([self.states(x, "f"), self.states(x, "b")], axis=2) @ self.p["W"] + self.p["c"]
        logits -= logits.max(axis=2, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(axis=2, keepdims=True)
        return logits

    def gradients(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
        """Mean cross entropy over all positions that hold a byte, and its gradient by backpropagation through time."""
        h, g, keeps = self.hidden, {k: np.zeros_like(v) for k, v in self.p.items()}, {"f": [], "b": []}
        s = np.concatenate([self.states(x, d, keeps[d]) for d in "fb"], axis=2)
        logits = s @ self.p["W"] + self.p["c"]
        logits -= logits.max(axis=2, keepdims=True)
        prob = np.exp(logits)
        prob /= prob.sum(axis=2, keepdims=True)
        real = (x < 256).astype(np.float32)[:, :, None]
        count = max(float(real.sum()), 1.0)
        hit = np.broadcast_to(y[None, :, None], (*x.shape, 1))
        loss = float(-(np.log(np.take_along_axis(prob, hit, 2) + 1e-9) * real).sum() / count)
        np.put_along_axis(prob, hit, np.take_along_axis(prob, hit, 2) - 1, 2)
        prob *= real / np.float32(count)
        g["W"] = np.einsum("tbh,tbc->hc", s, prob)
        g["c"] = prob.sum(axis=(0, 1))
        ds = prob @ self.p["W"].T
        for d, part in (("f", ds[:, :, :h]), ("b", ds[:, :, h:])):
            u, v, back = self.p["U" + d], self.p["V" + d], 0.0
            for t, s0, raw, z, r, n, c in reversed(keeps[d]):
                dh = part[t] + back
                dn = dh * z * (1 - n * n)
                dc = dn @ v.T
                dg = np.concatenate([dh * (n - s0), dc * s0], axis=1) * np.float32(0.25)
                dg[np.abs(raw) >= 2] = 0
                back = dh * (1 - z) + dc * r + dg @ u.T
                g["U" + d] += s0.T @ dg
                g["V" + d] += c.T @ dn
                np.add.at(g["E" + d], x[t], np.concatenate([dg, dn], axis=1))
        return loss, g

    def fit(self, x: np.ndarray, y: np.ndarray, cfg: Training) -> list[float]:
        """Adam with a falling rate over seeded batches.  x (N, WINDOW) bytes with 256 for padding, y (N,) language numbers."""
        rng, m, v, losses = np.random.default_rng(cfg.seed), {}, {}, []
        for step in range(1, cfg.steps + 1):
            at = rng.integers(0, len(x), cfg.batch)
            loss, g = self.gradients(np.ascontiguousarray(x[at].T), y[at])
            losses.append(loss)
            norm = float(np.sqrt(sum(float((a * a).sum()) for a in g.values())))
            rate = cfg.rate * min(1.0, 2 * (1 - step / (cfg.steps + 1))) * min(1.0, 1.0 / max(norm, 1e-9))
            for k, a in g.items():
                m[k] = 0.9 * m.get(k, 0) + 0.1 * a
                v[k] = 0.99 * v.get(k, 0) + 0.01 * a * a
                self.p[k] -= (rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
        return losses


def windows(raw: bytes) -> np.ndarray:
    """(n, WINDOW) byte values; the last window is padded with 256."""
    n = -(-len(raw) // WINDOW)
    out = np.full(n * WINDOW, 256, np.int16)
    out[:len(raw)] = np.frombuffer(raw, np.uint8)
    return out.reshape(n, WINDOW)


def bucket_of(id_col: str = "doc_id"):
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 4


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", cfg: Training = Training()) -> ByteGru | None:
    """Fit on labelled documents whose crc32(id as text) mod 4 is not 2.  None where no such document has text.

    About documents_per_language documents of each language are chosen by a hash of the id (all, if fewer), and
    windows_per_document windows of each, spread over the whole text: a sample bounded by these two parameters.
    """
    pool = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).cast("string").alias("t"), F.col(lang_col).cast("string").alias("l"))
    pool = pool.where((F.coalesce(bucket_of("i"), F.lit(0)) != 2) & F.col("l").isNotNull() & (F.length("t") > 0))
    counts = pool.groupBy("l").count()
    share = F.lit(2.0 * cfg.documents_per_language) / F.col("count")
    chance = (F.xxhash64(F.col("i"), F.lit(cfg.seed)) / F.lit(float(1 << 63)) + 1) / 2
    chosen = pool.join(F.broadcast(counts), "l").where(chance < share)

    def cut(batches):
        for b in batches:
            rows = [], [], []
            for i, t, lang in zip(*(c.to_pylist() for c in b.columns)):
                w = windows(t.encode("utf-8", "replace"))
                at = np.unique(np.linspace(0, len(w) - 1, cfg.windows_per_document).astype(int))
                for col, value in zip(rows, (i, lang, w[at].astype("<i2").tobytes())):
                    col.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], pa.int64()), pa.array(rows[1], pa.string()), pa.array(rows[2], pa.binary())], names=["i", "l", "w"])

    sample = sorted(chosen.select("i", "t", "l").mapInArrow(tidy(cut), "i long, l string, w binary").collect(), key=lambda r: (r.l, r.i is None, r.i or 0, r.w))
    languages = sorted({r.l for r in sample})
    if not languages:
        return None
    xs, ys = [], []
    for k, lang in enumerate(languages):
        own = [np.frombuffer(r.w, "<i2").reshape(-1, WINDOW) for r in sample if r.l == lang][:cfg.documents_per_language]
        x = np.concatenate(own)
        x = x[np.random.default_rng(k).permutation(len(x))]
        xs.append(x)
        ys.append(np.full(len(x), k))
    most = max(map(len, xs))
    x = np.concatenate([np.resize(a, (most, WINDOW)) for a in xs])
    y = np.concatenate([np.resize(a, most) for a in ys])
    model = ByteGru(languages, cfg.hidden, cfg.seed)
    model.fit(x.astype(np.int64), y, cfg)
    return model


def pooled(model: ByteGru, texts: list[str | None], rows: int = 4096) -> list[tuple[str, float]]:
    """(language, score) of each text: the mean distribution over all positions.  und and 0 without a letter."""
    out: list[tuple[str, float]] = [(UNDETERMINED, 0.0)] * len(texts)
    sums = np.zeros((len(texts), len(model.languages)))
    held: list[tuple[int, np.ndarray]] = []
    size = 0

    def flush():
        owner = np.repeat([k for k, _ in held], [len(w) for _, w in held])
        x = np.concatenate([w for _, w in held])
        for at in range(0, len(x), rows):
            part, own = x[at:at + rows], owner[at:at + rows]
            prob = model.positions(np.ascontiguousarray(part.T))
            prob[part.T == 256] = 0
            np.add.at(sums, own, prob.sum(axis=0, dtype=np.float64))

    for k, text in enumerate(texts):
        if text and _LETTER.search(text):
            held.append((k, windows(text.encode("utf-8", "replace"))))
            size += len(held[-1][1])
            if size >= 4 * rows:
                flush()
                held, size = [], 0
    if held:
        flush()
    for k in np.flatnonzero(sums.sum(axis=1) > 0):
        p = sums[k] / sums[k].sum()
        out[k] = (model.languages[int(p.argmax())], min(1.0, float(p.max())))
    return out


def predict(docs: DataFrame, model: ByteGru | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score.

    Null texts and texts without a letter, and all texts where there is no model, give und with score 0.  A null id counts as not
    held out.  Repeated rows give equal rows; equal scores go to the first language in code point order.
    """

    def run(batches):
        for b in batches:
            found = pooled(model, b.column(1).to_pylist()) if model else [(UNDETERMINED, 0.0)] * b.num_rows
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x[0] for x in found], pa.string()), pa.array([x[1] for x in found], pa.float64())],
                                             names=["doc_id", "lang_pred", "score"])

    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    found = d.mapInArrow(tidy(run), "doc_id long, lang_pred string, score double")
    return found.select("doc_id", F.coalesce(bucket_of() == 2, F.lit(False)).alias("held_out"), "lang_pred", "score")


def keep_determined(docs: DataFrame, model: ByteGru | None, text_col: str = "text") -> DataFrame:
    """The documents for which predict names a language, whatever its score, all columns as they were.

    The decision is made beside the row, in one pass over the input without a shuffle.  Without a model nothing is kept.
    """
    names = docs.columns

    def run(batches):
        for b in batches:
            found = pooled(model, b.column(names.index(text_col)).to_pylist()) if model else [(UNDETERMINED, 0.0)] * b.num_rows
            yield b.filter(pa.array([lang != UNDETERMINED for lang, _ in found], pa.bool_()))

    return docs.mapInArrow(tidy(run), docs.schema)
