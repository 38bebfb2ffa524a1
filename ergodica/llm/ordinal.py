"""Quality classification by cumulative-link (ordinal logistic) regression on graded ratings.

P(grade <= k | x) = sigmoid(threshold_k - w.x): one weight vector over hashed text features, shared by all grades, and ordered
thresholds (the first free, the others by positive steps). The expected grade and the tail probability P(grade >= top)
rank and select documents.

Features are the lower-cased words of the whole text and their first four and six letters, hashed, each with the root of its share of all words (a vector of unit
length, so long texts do not add up noise), and a few shares of character kinds. Weights exist only for words in at least ``LEAST_SHARE`` of the sample's documents, others are 0.
Fitted in numpy on the driver on a bounded sample of ``SAMPLE_DOCS`` rated documents; scoring is one narrow pass.

Defined results. Null or empty text: grade expectation 0, tail 0, not kept. No rated document: all grades equally likely,
all texts but null and empty ones kept. Repeated rows: judged alike. A tail of exactly ``least``: kept. Null doc_id: judged, never learnt from. Conflicting ratings of one document: its lowest grade. Extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_batches, slim

BITS = 20
SAMPLE_DOCS = 8000
LEAST_SHARE = 0.008
SHARES = 6
_STRIP = b".,;:!?\"'()[]*#$%&|<>"
_SYMBOLS = bytes(c for c in b"#*$%&|<>@^~_=+\\/")
_DIGITS = b"0123456789"


def features(text: str | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashed words, roots of their shares, shares of character kinds)."""
    raw = (text or "").encode()
    words = raw.lower().split()
    count: Counter = Counter()
    for word, n in Counter(words).items():
        bare = word.strip(_STRIP).decode(errors="replace")
        for part in {bare, f"{bare[:4]}^", f"{bare[:6]}^"}:
            count[part] += n
    ids = np.fromiter((xxhash.xxh3_64_intdigest(w) & ((1 << BITS) - 1) for w in count), np.int64, len(count))
    ids, at = np.unique(ids, return_inverse=True)
    tf = np.bincount(at, np.fromiter(count.values(), np.float64, len(count)), minlength=len(ids))
    n, k = max(1, len(raw)), max(1, len(words))
    symbols, digits = n - len(raw.translate(None, _SYMBOLS)), n - len(raw.translate(None, _DIGITS))
    shares = [min(1.0, 5 * symbols / n), min(1.0, 5 * digits / n), len(set(words)) / k, min(1.0, k / 50), min(3.0, raw.count(b"\n") / k * 10), min(2.0, n / k / 10)]
    return ids, (np.sqrt(tf / k) * 6).astype(np.float32), np.array(shares) * bool(words)


class CumulativeLink:
    def __init__(self, grades: int):
        self.grades = grades
        self.words = np.zeros(1 << BITS, np.float32)
        self.shares = np.zeros(SHARES)
        self.base, self.steps = 0.0, np.zeros(max(0, grades - 2))

    @property
    def thresholds(self) -> np.ndarray:
        return self.base + np.concatenate([[0.0], np.cumsum(np.exp(self.steps))]) if self.grades > 1 else np.zeros(0)

    def latent(self, ids: np.ndarray, roots: np.ndarray, shares: np.ndarray) -> float:
        return float(self.words[ids] @ roots + self.shares @ shares)

    def tails(self, latent: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 1 .. grades - 1."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - np.asarray(latent)[:, None], -40, 40)))

    def slopes(self, grade: int, latent: float) -> tuple[float, float, np.ndarray]:
        """Negative log likelihood of a document's grade, and its derivatives by the latent value and by each threshold."""
        c = 1 / (1 + np.exp(np.clip(latent - self.thresholds, -40, 40)))  # P(grade <= k)
        has_up, has_low = grade < self.grades - 1, grade > 0
        up, low = (c[grade] if has_up else 1.0), (c[grade - 1] if has_low else 0.0)
        p = max(up - low, 1e-9)
        d_up, d_low = (up * (1 - up) / p if has_up else 0.0), (low * (1 - low) / p if has_low else 0.0)
        d_t = np.zeros(len(c))
        if has_up:
            d_t[grade] -= d_up
        if has_low:
            d_t[grade - 1] += d_low
        return float(-np.log(p)), d_up - d_low, d_t

    def fit(self, texts: list[str], y: np.ndarray, epochs: int = 15, l2: float = 0.1, seed: int = 3) -> CumulativeLink:
        """Adagrad on the exact negative log likelihood, grades weighted by the root of their rarity."""
        rng = np.random.default_rng(seed)
        rows = [features(t) for t in texts]
        seen = np.bincount(np.concatenate([r[0] for r in rows]), minlength=1 << BITS) >= max(3, LEAST_SHARE * len(texts))
        rows = [(ids[seen[ids]], x[seen[ids]], s) for ids, x, s in rows]
        share = np.bincount(y, minlength=self.grades) / len(y)
        weight = np.sqrt(1 / np.maximum(share, 1e-3))
        g_words, g_shares, g_base, g_steps = np.full(1 << BITS, 1e-3, np.float32), np.full(SHARES, 1e-2), 1e-2, np.full(len(self.steps), 1e-2)
        for epoch in range(epochs):
            rate = 0.5 / (1 + 0.3 * epoch)
            for i in rng.permutation(len(rows)):
                ids, x, s = rows[i]
                _, d_z, d_t = self.slopes(int(y[i]), self.words[ids] @ x + self.shares @ s)
                d_z, d_t = weight[y[i]] * d_z, weight[y[i]] * d_t
                g = np.float32(d_z) * x + np.float32(l2) * self.words[ids]
                g_words[ids] += g * g
                self.words[ids] -= np.float32(rate) * g / np.sqrt(g_words[ids])
                gs = d_z * s
                g_shares += gs * gs
                self.shares -= rate * gs / np.sqrt(g_shares)
                g_base += d_t.sum() ** 2
                self.base -= rate * d_t.sum() / np.sqrt(g_base)
                if len(self.steps):
                    d_steps = np.cumsum(d_t[::-1])[::-1][1:] * np.exp(self.steps)
                    g_steps += d_steps**2
                    self.steps -= rate * d_steps / np.sqrt(g_steps)
        return self


def grades(labels: DataFrame) -> DataFrame:
    """doc_id, grade: 0 toxic, 1 neither toxic nor good, 2 good; a document's lowest where ratings conflict."""
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 0, 1).when(F.col("quality") == 1, 2)
    return slim(labels, "doc_id", "quality", "toxic").select("doc_id", grade.alias("grade")).where("doc_id is not null and grade is not null").groupBy("doc_id").agg(F.min("grade").alias("grade"))


def train(docs: DataFrame, rated: DataFrame, count: int = 3, sample_docs: int = SAMPLE_DOCS) -> CumulativeLink | None:
    """``rated``: doc_id, grade (0 to count - 1). The sample is the ``sample_docs`` rated documents with the least id hash."""
    order = F.xxhash64("doc_id", F.lit(2))
    chosen = rated.withColumn("o", order).orderBy("o").limit(sample_docs)
    if (bound := chosen.agg(F.max("o")).first()[0]) is None:
        return None
    few = rated.where(order <= bound)
    rows = slim(docs, "doc_id", "text").where((order <= bound) & F.col("text").isNotNull()).join(few, "doc_id").select("doc_id", "text", "grade")
    rows = rows.orderBy(order, "doc_id", F.xxhash64("text"), "text").limit(4 * sample_docs)  # a document's repeated rows come in a fixed order
    rows = sorted((r.doc_id, r.text, r.grade) for r in rows.collect())
    if not rows:
        return None
    return CumulativeLink(count).fit([r[1] for r in rows], np.array([r[2] for r in rows]))


def score(docs: DataFrame, model: CumulativeLink | None, least: float = 0.93, top: int = 1) -> DataFrame:
    """doc_id, expected_grade, tail (P(grade >= top)), kept (tail >= least) for every row."""
    held = None if model is None else (model.grades, model.words[model.words != 0], np.flatnonzero(model.words), model.shares, model.base, model.steps)

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        texts = t.column("text").to_pylist()
        some = np.array([bool(x) for x in texts])
        if held is None:
            tails = np.full((len(texts), 2), [2 / 3, 1 / 3])  # three grades, equally likely
        else:
            m = CumulativeLink(held[0])
            m.words[held[2]] = held[1]
            m.shares, m.base, m.steps = held[3:]
            tails = m.tails(np.array([m.latent(*features(x)) for x in texts]))
        tails = tails * some[:, None]
        tail = tails[:, top - 1]
        keep = some if held is None else (tail >= least) & some
        yield pa.table([t.column("doc_id"), pa.array(tails.sum(axis=1)), pa.array(tail), pa.array(keep)], names=["doc_id", "expected_grade", "tail", "kept"])

    return in_batches(slim(docs, "doc_id", "text"), kernel, "doc_id long, expected_grade double, tail double, kept boolean")
