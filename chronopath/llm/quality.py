"""Quality scores from pairwise preferences (Bradley-Terry).

Every labelled good document is preferred to every labelled bad one. The chance
that a document wins a pair is the logistic function of the difference of two
linear scores, so the weights are a logistic fit, without bias, on differences of
features. Features are shares of a text's characters, words and lines, and a
hashed histogram of word shapes; they do not depend on length. A document's score
between 0 and 1 is then fitted on its margin; ``keep_top`` thresholds by a
quantile of the scores.

The fit uses about ``FIT_ROWS`` labelled rows at most, chosen by a hash of their id,
and ``PAIRS`` preference pairs drawn from them by a fixed generator.

Edge cases: null and empty texts have the features of no words; with one class
missing every score is the share of label 1 (0 with no labels); repeated rows are
scored each; ties at a quantile are kept; other columns pass through.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import MEMO_ENTRIES, words
from chronopath.llm.labelled import add_scores, attach, fold, logistic, sample, sigmoid

FIT_ROWS, PAIRS, SHAPES = 20_000, 60_000, 128
THRESHOLD = 0.3

#: Character classes of a byte: lower, upper, digit, white space, ending punctuation, other symbols, beyond ASCII.
CLASSES = 7
_CLASS = np.full(256, 6, np.uint8)
_CLASS[:128] = 5
for _k, _set in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" \t\n\r\x0b\x0c", b".,;:!?'\"()-")):
    _CLASS[list(_set)] = _k
_RUNS = re.compile(rb"([a-z]|[^\x00-\x7f])+|[A-Z]+|[0-9]+")


def shape(word: bytes) -> int:
    """Bucket of a word's shape: runs of letters and digits become one sign, the rest stays (up to 12 bytes)."""
    sign = _RUNS.sub(lambda m: b"a" if m[1] is not None else b"A" if m[0][:1].isalpha() else b"0", word)[:12]
    return zlib.crc32(sign) % SHAPES


class Shapes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= MEMO_ENTRIES:
            self.clear()
        self[word] = found = shape(word)
        return found


def features(text: str | None, shapes: Shapes) -> np.ndarray:
    raw, tokens = (text or "").encode("utf-8", "surrogatepass"), words(text)
    n, size = max(1, len(tokens)), max(1, len(raw))
    chars = np.bincount(_CLASS[np.frombuffer(raw, np.uint8)], minlength=CLASSES) / size
    counts = Counter(tokens)
    top = counts.most_common(3)
    pairs = Counter(zip(tokens, tokens[1:]))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    sizes = np.fromiter(map(len, tokens), np.float64, len(tokens)) if tokens else np.zeros(1)
    form = np.bincount(np.fromiter(map(shapes.__getitem__, tokens), np.int64, len(tokens)), minlength=SHAPES) / n
    expected = n ** 0.75  # of a vocabulary that grows as usual
    general = [
        len(counts) / n, min(1.0, len(counts) / expected), sum(c for _, c in top) / n, len(pairs) / max(1, n - 1),
        sum(a == b for a, b in zip(tokens, tokens[1:])) / n, sizes.mean() / 10, sizes.std() / 10, sizes.max() / 50,
        len(set(lines)) / max(1, len(lines)), min(1.0, len(lines) / n * 5), sum(x.count(b"|") for x in lines) / n,
        len(zlib.compress(raw, 1)) / size, float(not tokens), min(1.0, 20 / n),
    ]
    return np.concatenate([np.sqrt(chars), general, np.sqrt(form)])


@dataclass
class Ranking:
    weights: np.ndarray
    slope: float = 1.0
    offset: float = 0.0
    constant: float | None = None

    def margin(self, x: np.ndarray) -> np.ndarray:
        return x @ self.weights

    def scorer(self):
        shapes = Shapes()

        def score(texts: list[str | None]) -> list[np.ndarray]:
            if self.constant is not None:
                return [np.full(len(texts), self.constant), np.zeros(len(texts))]
            margin = self.margin(np.array([features(t, shapes) for t in texts]).reshape(len(texts), -1))
            return [sigmoid(self.slope * margin + self.offset), margin]

        return score


SCORES = {"score": "double", "margin": "double"}
_NAMES = [f"f{i}" for i in range(CLASSES + 14 + SHAPES)]


def fit(labelled: DataFrame, rows: int = FIT_ROWS, pairs: int = PAIRS, ridge: float = 3.0) -> Ranking:
    """Learn from (id, text, label)."""
    extracted = add_scores(sample(labelled.select("id", "text", "label"), rows), "text", dict.fromkeys(_NAMES, "double"), lambda: (lambda shapes=Shapes(): lambda texts: list(np.array([features(t, shapes) for t in texts]).reshape(len(texts), -1).T))()).drop("text").toArrow().to_pandas().sort_values("id")
    y, x = extracted.label.to_numpy(float), extracted[_NAMES].to_numpy(float)
    if len(np.unique(y)) < 2:
        return Ranking(np.zeros(len(_NAMES)), constant=float(y.mean()) if len(y) else 0.0)
    rng = np.random.default_rng(7)
    good, bad = rng.choice(np.flatnonzero(y == 1), pairs), rng.choice(np.flatnonzero(y == 0), pairs)
    weights = bradley_terry(x[good] - x[bad], ridge)
    _, scale, (bias, slope) = logistic((x @ weights)[:, None], y)
    centre = (x @ weights).mean()
    return Ranking(weights, slope / scale[0], bias - slope / scale[0] * centre)


def bradley_terry(difference: np.ndarray, ridge: float = 3.0, rounds: int = 40) -> np.ndarray:
    """Weights that make each row's winner likeliest: logistic loss on feature differences, no bias."""
    scale = np.sqrt((difference**2).mean(axis=0)) + 1e-6
    z, w = difference / scale, np.zeros(difference.shape[1])
    for _ in range(rounds):
        p = sigmoid(z @ w)
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge * np.eye(len(w)), ridge * w - z.T @ (1 - p))
        w -= step / max(1.0, np.abs(step).max())
        if np.abs(step).max() < 1e-6:
            break
    return w / scale


def score(docs: DataFrame, model: Ranking, text_col: str = "text") -> DataFrame:
    """All columns of ``docs`` with ``score`` and ``margin``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return add_scores(docs, text_col, SCORES, lambda: shared.value.scorer())


def keep_top(scored: DataFrame, share: float, score_col: str = "score") -> DataFrame:
    """Rows whose score reaches the quantile that leaves about ``share`` of them (ties are kept)."""
    (least,) = scored.agg(F.percentile_approx(score_col, 1 - share, 10_000)).first()
    return scored.where(F.col(score_col) >= F.lit(least)) if least is not None else scored


def fit_tables(docs: DataFrame, labels: DataFrame) -> Ranking:
    """Learn ``labels.quality`` from the rows outside the held-out fifth."""
    return fit(attach(docs, labels, "quality").where(fold("id", 5) != 0))


def op10_quality(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    scored = score(docs, fit_tables(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), "margin")
