"""Toxicity by cumulative-link ordinal regression on sparse text features.

Grades run from 0 (clean) to 3.  Labels say only toxic or not, so the grade of a toxic training text is its
place among the toxic ones by how many different words it has that the toxic texts use and the clean ones do not
(terciles, by the same ratio): a harsher text uses more of them.  One weight vector is shared by all thresholds:
P(grade >= k) = logistic(w.x - t_k) with t_1 < t_2 < t_3, kept in order by learning the gaps' logarithms.
Features are hashed words, present or not.  How high their likelihood ratio between toxic and clean sampled
texts must be for them to carry weight follows from the sample: of ``TELLING``, which begins with 0 (all
words), the value with the least deviance on held-out folds.  The output is the expected severity, the sum
of the P(grade >= k).

Defined cases: null and empty texts have no features and are clean; texts are
read whole; labels without a document and null labels are ignored; without any label nothing is toxic;
repeated rows are each scored; ids may be of any type; where a column of ``docs`` is named like one made here,
that gets underscores until it has a name of its own.  Labels are a sample of at most ``MOST`` rows and about
``MOST_FEATURES`` words.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .labelled import fitted, training_set
from .store import worker_cache
from .text import WordHashes, alnum_words, as_bytes, pieces, unused

MOST = 20_000
MOST_FEATURES = 8_000_000
FEATURE_BITS = 31
GRADES = 3
TELLING = (0.0, 3.0, 6.0, 9.0, 12.0, 16.0, 25.0)
FOLDS = 3
#: Probabilities count as this far from 0 and 1 in the deviance, so single wrong labels don't decide.
DOUBT = 1e-3
STEPS, FOLD_STEPS = 1000, 150
L2 = 0.1
THRESHOLD = 0.5


def features(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of the distinct words of each text, and how often each occurs."""
    hashes = worker_cache().setdefault("toxicity words", WordHashes())
    for text in texts:
        place = (hashes.of(alnum_words(text)) >> np.uint64(64 - FEATURE_BITS)).astype(np.int32)
        place.sort()
        first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]])) if len(place) else np.empty(0, np.int64)
        yield place[first], np.diff(first, append=len(place)).astype(np.float32)


def ratios(rows: list[tuple[int, int, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features, the likelihood ratio of each one's presence against the label, and which are the toxic texts' own; equal texts count once."""
    once = {(label, at.tobytes()): at for _, label, at, _ in rows}
    sizes = np.array([sum(label == k for label, _ in once) for k in (0, 1)], float)
    known, place = np.unique(np.concatenate([*once.values(), np.empty(0, np.int32)]), return_inverse=True)
    owner = np.concatenate([np.full(len(at), label) for (label, _), at in once.items()] or [np.empty(0, np.int64)]).astype(np.int64)
    counts = np.bincount(owner * len(known) + place, minlength=2 * len(known)).reshape(2, len(known)).astype(float)
    total, all_ = counts.sum(0), max(sizes.sum(), 1)
    ratio = np.zeros(len(known))
    for k in (0, 1):
        for part, held in ((counts[k], total), (sizes[k] - counts[k], all_ - total)):
            expected = np.maximum(held * sizes[k] / all_, 1e-12)
            ratio += 2 * np.where(part > 0, part * np.log(np.maximum(part, 1e-12) / expected), 0)
    return known, ratio, counts[1] * sizes[0] > counts[0] * sizes[1]


def members(at: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which of ``at`` are in the sorted ``known``, and where."""
    if not len(known):
        return np.zeros(len(at), bool), np.empty(0, np.int64)
    place = np.minimum(np.searchsorted(known, at), len(known) - 1)
    found = known[place] == at
    return found, place[found]


def grades(rows: list[tuple[int, int, np.ndarray, np.ndarray]], toxic_words: np.ndarray) -> np.ndarray:
    """Severity grades of the sample: 0 for clean texts, terciles of the variety of toxic words for others."""
    y = np.array([r[1] for r in rows])
    variety = np.array([len(members(at, toxic_words)[1]) for _, _, at, _ in rows])
    out = np.zeros(len(rows), np.int64)
    hot = np.flatnonzero(y == 1)
    if len(hot):
        out[hot] = 1 + np.searchsorted(np.quantile(variety[hot], [i / GRADES for i in range(1, GRADES)]), variety[hot], "right")
    return np.minimum(out, GRADES)


class OrdinalModel:
    """Shared weights and ordered thresholds, fitted by Adagrad on the cumulative-link likelihood."""

    def __init__(self):
        self.known, self.w = np.empty(0, np.int32), np.empty(0)
        self.first, self.gaps = 1.0, np.zeros(GRADES - 1)

    def thresholds(self) -> np.ndarray:
        return self.first + np.concatenate([[0.0], np.cumsum(np.exp(self.gaps))])

    @staticmethod
    def _cumulative(eta: np.ndarray, t: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 0 to GRADES + 1."""
        inner = 1 / (1 + np.exp(-np.clip(eta[:, None] - t[None, :], -30, 30)))
        return np.concatenate([np.ones((len(eta), 1)), inner, np.zeros((len(eta), 1))], 1)

    def fit(self, rows: list[tuple[int, int, np.ndarray, np.ndarray]]) -> "OrdinalModel":
        if not rows:
            self.first = 30.0
            return self
        return self.weigh(rows, ratios(rows), chosen_cut(rows))

    def weigh(self, rows: list[tuple[int, int, np.ndarray, np.ndarray]], of: tuple[np.ndarray, np.ndarray, np.ndarray], cut: float, steps: int | None = None, l2: float = L2, rate: float = 0.5) -> "OrdinalModel":
        """Fits the weights of the features whose ratio reaches ``cut``."""
        used = of[1] >= cut
        known, toxic_words = of[0][used], of[2][used]
        y = grades(rows, known[toxic_words])
        places = [members(at, known)[1] for _, _, at, _ in rows]
        owner, column = np.repeat(np.arange(len(rows)), [len(p) for p in places]), np.concatenate(places)
        w, gw, gt, n = np.zeros(len(known)), np.full(len(known), 1e-8), np.full(GRADES, 1e-8), len(rows)
        theta = np.concatenate([[self.first], self.gaps])
        for _ in range(steps or STEPS):
            eta = np.bincount(owner, w[column], n)
            self.first, self.gaps = theta[0], theta[1:]
            c = self._cumulative(eta, self.thresholds())
            slope = c * (1 - c)
            i = np.arange(n)
            p = np.maximum(c[i, y] - c[i, y + 1], 1e-9)
            d_eta = -(slope[i, y] - slope[i, y + 1]) / p / n
            d_t = np.zeros(GRADES + 2)
            np.add.at(d_t, y, slope[i, y] / p / n)
            np.add.at(d_t, y + 1, -slope[i, y + 1] / p / n)
            d_t = d_t[1:-1]
            d_theta = np.array([d_t.sum(), *[d_t[k:].sum() * np.exp(self.gaps[k - 1]) for k in range(1, GRADES)]])
            d_w = np.bincount(column, d_eta[owner], len(known)) + l2 * w / n
            gw += d_w * d_w
            gt += d_theta * d_theta
            w -= rate * d_w / np.sqrt(gw)
            theta -= rate * d_theta / np.sqrt(gt)
        self.known, self.w, self.first, self.gaps = known, w, theta[0], theta[1:]
        return self

    def dot(self, at: np.ndarray) -> float:
        return float(self.w[members(at, self.known)[1]].sum())

    def severity(self, eta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Expected grade and P(grade >= 1)."""
        c = self._cumulative(eta, self.thresholds())[:, 1:-1]
        return c.sum(1), c[:, 0]


def chosen_cut(rows: list[tuple[int, int, np.ndarray, np.ndarray]]) -> float:
    """The one of ``TELLING`` with the least deviance on held-out folds; equal texts share a fold, labels are dealt evenly."""
    fold, seen = {}, [0, 0]
    for text, label in sorted({at.tobytes(): label for _, label, at, _ in rows}.items(), key=lambda kv: (zlib.crc32(kv[0]), kv[0])):
        fold[text], seen[label] = seen[label] % FOLDS, seen[label] + 1
    loss = dict.fromkeys(TELLING, 0.0)
    for k in range(FOLDS):
        inner = [r for r in rows if fold[r[2].tobytes()] != k]
        outer = [r for r in rows if fold[r[2].tobytes()] == k]
        if not inner or not outer:
            continue
        of, toxic = ratios(inner), np.array([r[1] for r in outer]) == 1
        for cut in TELLING:
            model = OrdinalModel().weigh(inner, of, cut, FOLD_STEPS)
            p = np.clip(model.severity(np.array([model.dot(r[2]) for r in outer]))[1], DOUBT, 1 - DOUBT)
            loss[cut] -= float(np.log(np.where(toxic, p, 1 - p)).sum())
    return min(TELLING, key=lambda cut: (loss[cut], cut))


def train(docs: DataFrame, labels: DataFrame, column: str = "toxic", most: int = MOST, passes=lambda x: x) -> OrdinalModel:
    model = OrdinalModel()
    vars(model).update(fitted(training_set(docs, labels, column, features, most, passes), lambda rows: vars(OrdinalModel().fit(rows)), most, MOST_FEATURES))
    return model


def made_names(columns: list[str]) -> tuple[str, str]:
    """Names of the columns that ``score`` adds to these."""
    return unused(columns, "_severity"), unused(columns, "_p_toxic")


def score(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """``docs`` with ``_severity`` (expected grade) and ``_p_toxic``."""
    grade, chance = made_names(docs.columns)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            for piece in pieces(batch):
                eta = np.array([model.dot(at) for at, _ in features(as_bytes(piece.column("text")))])
                severity, toxic = model.severity(eta)
                yield pa.RecordBatch.from_arrays([*piece.columns, pa.array(severity, pa.float64()), pa.array(toxic, pa.float64())], [*piece.schema.names, grade, chance])

    return docs.mapInArrow(run, docs.select(*docs.columns, F.lit(0.0).alias(grade), F.lit(0.0).alias(chance)).schema)


def report(docs: DataFrame, labels: DataFrame, most: int = MOST) -> DataFrame:
    """Per document: doc_id, severity, grade (nearest), p_toxic, toxic."""
    scored = score(docs.select("doc_id", "text"), train(docs, labels, most=most))
    return scored.select("doc_id", F.col("_severity").alias("severity"), F.round("_severity").cast("int").alias("grade"), F.col("_p_toxic").alias("p_toxic"), (F.col("_p_toxic") >= THRESHOLD).alias("toxic"))


def keep_civil(docs: DataFrame, labels: DataFrame, most: int = MOST) -> DataFrame:
    """Documents that are not toxic, with the columns of ``docs``."""
    return score(docs, train(docs, labels, most=most)).where(F.col(made_names(docs.columns)[1]) < THRESHOLD).select(*docs.columns)
