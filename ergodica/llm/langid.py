"""Language identification by a bidirectional gated recurrent network over UTF-8 bytes.

The network reads a text in segments of ``SEGMENT`` bytes (the state starts anew in each), labels **every** byte of the
whole text with class probabilities from both directions, and pools them by the mean over all bytes of the document.
It is trained on the driver, in numpy, by backpropagation through time, from a bounded sample of labelled documents;
prediction is one narrow pass (no shuffle) whose only constant is the weights (some 60 KB).

Defined results. Null text, empty text or text without a letter: ``und`` with score 0. No labelled document to learn
from: every text is ``und``. Repeated rows are predicted alike, each on its own. Null ``doc_id``: the row is kept,
``held_out`` is null and it is not learnt from. Equal probabilities: the language first in the alphabet. Texts of any length are read whole, 2,048 segments at a time. Extra columns of the input are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_batches, slim

SEGMENT = 64  # bytes a recurrent run covers
HIDDEN = 10  # units of each direction
SAMPLE_DOCS = 1200  # at most so many labelled documents are learnt from
STEPS = 260
BATCH = 192


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


class ByteTagger:
    """Two gated recurrent layers, one from each side, and a softmax over their joined states at every byte."""

    def __init__(self, classes: list[str], hidden: int = HIDDEN, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.classes, self.hidden = classes, hidden
        h = hidden
        self.w: dict[str, np.ndarray] = {}
        for side in "fb":
            self.w[f"in_{side}"] = rng.normal(0, 0.3, (257, 3 * h)).astype(np.float32)  # row 256: padding
            self.w[f"gate_{side}"] = rng.normal(0, 1 / np.sqrt(h), (h, 2 * h)).astype(np.float32)
            self.w[f"cand_{side}"] = rng.normal(0, 1 / np.sqrt(h), (h, h)).astype(np.float32)
        self.w["out"] = rng.normal(0, 0.3, (2 * h, max(1, len(classes)))).astype(np.float32)
        self.w["bias"] = np.zeros(max(1, len(classes)), np.float32)

    def _run(self, side: str, ids: np.ndarray, keep: bool) -> tuple[np.ndarray, list]:
        """ids: (time, rows). States at every position, and what backpropagation needs."""
        h, (steps, rows) = self.hidden, ids.shape
        into, gate, cand = self.w[f"in_{side}"], self.w[f"gate_{side}"], self.w[f"cand_{side}"]
        out, tape = np.empty((steps, rows, h), np.float32), []
        state = np.zeros((rows, h), np.float32)
        for t in range(steps) if side == "f" else range(steps - 1, -1, -1):
            x = into[ids[t]]
            g = _sigmoid(x[:, : 2 * h] + state @ gate)
            reset, keep_old = g[:, :h], g[:, h:]
            c = np.tanh(x[:, 2 * h :] + (reset * state) @ cand)
            new = c + keep_old * (state - c)
            if keep:
                tape.append((t, state, reset, keep_old, c))
            state = out[t] = new
        return out, tape

    def probabilities(self, ids: np.ndarray) -> np.ndarray:
        """(time, rows) byte ids to (time, rows, classes)."""
        both = np.concatenate([self._run("f", ids, False)[0], self._run("b", ids, False)[0]], axis=2)
        z = both @ self.w["out"] + self.w["bias"]
        z = np.exp(z - z.max(axis=2, keepdims=True))
        return z / z.sum(axis=2, keepdims=True)

    def gradients(self, ids: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean cross entropy over the bytes that are not padding, and its gradient through time."""
        h, grad = self.hidden, {k: np.zeros_like(v) for k, v in self.w.items()}
        states, tapes = {}, {}
        for side in "fb":
            states[side], tapes[side] = self._run(side, ids, True)
        both = np.concatenate([states["f"], states["b"]], axis=2)
        z = both @ self.w["out"] + self.w["bias"]
        z = np.exp(z - z.max(axis=2, keepdims=True))
        p = z / z.sum(axis=2, keepdims=True)
        real = (ids < 256).astype(np.float32)
        total = max(1.0, float(real.sum()))
        picked = np.take_along_axis(p, np.broadcast_to(y[None, :, None], (*ids.shape, 1)), axis=2)[..., 0]
        loss = float(-(np.log(picked + 1e-9) * real).sum() / total)
        d = p.copy()
        np.put_along_axis(d, np.broadcast_to(y[None, :, None], (*ids.shape, 1)), (picked - 1)[..., None], axis=2)
        d *= (real / total)[..., None]
        grad["out"] = np.einsum("trh,trc->hc", both, d)
        grad["bias"] = d.sum(axis=(0, 1))
        d_both = d @ self.w["out"].T
        for side, d_out in (("f", d_both[..., :h]), ("b", d_both[..., h:])):
            gate, cand = self.w[f"gate_{side}"], self.w[f"cand_{side}"]
            carry = np.zeros((ids.shape[1], h), np.float32)
            for t, old, reset, keep_old, c in reversed(tapes[side]):
                d_new = carry + d_out[t]
                d_c = d_new * (1 - keep_old) * (1 - c * c)
                d_ro = d_c @ cand.T
                d_g = np.concatenate([d_ro * old * reset * (1 - reset), d_new * (old - c) * keep_old * (1 - keep_old)], axis=1)
                grad[f"cand_{side}"] += (reset * old).T @ d_c
                grad[f"gate_{side}"] += old.T @ d_g
                dx = np.concatenate([d_g, d_c], axis=1)
                order = np.argsort(ids[t], kind="stable")
                at = np.flatnonzero(np.diff(ids[t][order], prepend=-1))
                grad[f"in_{side}"][ids[t][order][at]] += np.add.reduceat(dx[order], at, axis=0)
                carry = d_new * keep_old + d_ro * reset + d_g @ gate.T
        return loss, grad

    def fit(self, segments: np.ndarray, y: np.ndarray, steps: int = STEPS, seed: int = 11) -> ByteTagger:
        """Adam on random batches; segments: (rows, time) byte ids with 256 for padding."""
        rng = np.random.default_rng(seed)
        m, v = ({k: np.zeros_like(x) for k, x in self.w.items()} for _ in range(2))
        for step in range(1, steps + 1):
            rows = rng.integers(0, len(segments), min(BATCH, 4 * len(segments)))
            _, grad = self.gradients(np.ascontiguousarray(segments[rows].T), y[rows])
            norm = np.sqrt(sum(float((g * g).sum()) for g in grad.values()))
            rate = 0.03 * (1 - 0.9 * step / steps)
            for k, g in grad.items():
                g = g / max(1.0, norm)
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.99 * v[k] + 0.01 * g * g
                self.w[k] = (self.w[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
        return self

    def pooled(self, texts: list[bytes], rows: int = 2048) -> np.ndarray:
        """Mean class probabilities over all bytes of each text; a text without bytes has zeros."""
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        pieces = -(-lengths // SEGMENT)
        owner = np.repeat(np.arange(len(texts)), pieces)
        flat = np.frombuffer(b"".join(texts), np.uint8)
        starts = np.repeat(np.cumsum(lengths) - lengths, pieces) + SEGMENT * (np.arange(len(owner)) - np.repeat(np.cumsum(pieces) - pieces, pieces))
        ends = np.repeat(np.cumsum(lengths), pieces)
        total = np.zeros((len(texts), len(self.classes)))
        for a in range(0, len(owner), rows):
            at = starts[a : a + rows, None] + np.arange(SEGMENT)
            inside = at < ends[a : a + rows, None]
            ids = np.where(inside, flat[np.minimum(at, len(flat) - 1)].astype(np.int16), np.int16(256))
            p = self.probabilities(np.ascontiguousarray(ids.T)) * inside.T[..., None]
            np.add.at(total, owner[a : a + rows], p.sum(axis=0))
        return total / np.maximum(lengths, 1)[:, None]


def segments_of(texts: list[bytes], y: list[int], each: int = 24, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Random segments from anywhere in the whole texts, padded with 256."""
    rng = np.random.default_rng(seed)
    ids, labels = [], []
    for text, label in zip(texts, y, strict=True):
        raw = np.frombuffer(text, np.uint8).astype(np.int16)
        for at in rng.integers(0, max(1, len(raw) - SEGMENT + 1), min(each, 1 + len(raw) // SEGMENT)):
            cut = raw[at : at + SEGMENT]
            ids.append(np.concatenate([cut, np.full(SEGMENT - len(cut), 256, np.int16)]))
            labels.append(label)
    return np.array(ids, np.int16).reshape(-1, SEGMENT), np.array(labels, np.int64)


def fold(doc_id: str = "doc_id") -> F.Column:
    """0 to 4; documents of fold 0 are held out."""
    return F.crc32(F.col(doc_id).cast("string")) % 5


def train(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> ByteTagger | None:
    """Learn from text and non-null lang of documents outside fold 0; the sample is the ``sample_docs`` with the least id hash."""
    labelled = slim(docs, "doc_id", "text", "lang").where((fold() != 0) & F.col("lang").isNotNull() & F.col("text").rlike(r"\p{L}"))
    order = F.xxhash64("doc_id", F.lit(1))
    ids = labelled.select(order.alias("o")).orderBy("o").limit(sample_docs)
    bound = ids.agg(F.max("o")).first()[0]
    if bound is None:
        return None
    few = labelled.where(order <= bound).select("text", "lang", order.alias("o")).orderBy("o", "lang", F.xxhash64("text"), "text")
    rows = few.limit(4 * sample_docs).collect()  # ids may repeat: bounded all the same, and the same rows on every run
    rows.sort(key=lambda r: (r.o, r.lang, r.text))
    classes = sorted({r.lang for r in rows})
    ids_, y = segments_of([r.text.encode() for r in rows], [classes.index(r.lang) for r in rows])
    return ByteTagger(classes).fit(ids_, y)


def identify(docs: DataFrame, model: ByteTagger | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row of ``docs``."""
    base = slim(docs, "doc_id", "text")
    prepared = base.select("doc_id", (fold() == 0).alias("held_out"), F.when(F.col("text").rlike(r"\p{L}"), F.col("text")).alias("text"))
    return in_batches(prepared, tagging_kernel(model), "doc_id long, held_out boolean, lang_pred string, score double")


def tagging_kernel(model: ByteTagger | None):
    def kernel(t: pa.Table) -> Iterator[pa.RecordBatch]:
        texts = [(x or "").encode() for x in t.column("text").to_pylist()]
        rest = [c for c in t.column_names if c != "text"]
        if model is None or not texts:
            pred, score = ["und"] * len(texts), np.zeros(len(texts))
        else:
            p = model.pooled(texts)
            best = p.argmax(axis=1)
            some = np.fromiter(map(len, texts), np.int64, len(texts)) > 0
            pred = [model.classes[b] if s else "und" for b, s in zip(best, some, strict=True)]
            score = np.clip(np.where(some, p.max(axis=1), 0.0), 0.0, 1.0)
        yield pa.table([*(t.column(c) for c in rest), pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=[*rest, "lang_pred", "score"])

    return kernel


def filter_languages(docs: DataFrame, model: ByteTagger | None, accepted: list[str] | None = None, least: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose predicted language is accepted (null: any that was learnt) with a pooled probability of ``least`` or more."""
    names = docs.columns
    marked = docs.withColumns({"__text": F.when(F.col("text").rlike(r"\p{L}"), F.col("text"))})
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    inner = tagging_kernel(model)

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        for out in inner(pa.table([t.column("__text")], names=["text"])):
            pred, score = out.column("lang_pred").to_pylist(), out.column("score").to_pylist()
            yes = [p != "und" and s >= least and (accepted is None or p in accepted) for p, s in zip(pred, score, strict=True)]
            yield t.select(names).filter(pa.array(yes, pa.bool_()))

    return in_batches(marked, kernel, fields)
