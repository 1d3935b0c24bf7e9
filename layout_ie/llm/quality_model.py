"""Quality classifier: ordinal cumulative-link regression on graded ratings.

Grades are ordered: 0 toxic, 1 poor, 2 good.  A text is the set of its hashed features:
words without case and punctuation, the shapes that their case and punctuation give, and
how much of the text repeats.  One weight a
feature is shared by all grades; ordered thresholds t turn the score s into
P(grade <= k) = 1 / (1 + exp(s - t_k)).  The expected grade and the probability of the
top grade select documents.

The model is fitted on at most ``SAMPLE`` labelled documents, taken by hash of
their id; it keeps features of ``LEAST_DOCS`` sampled documents or more whose documents' grades
differ from the sample's by ``SCREEN`` standard errors, at most ``MAX_FEATURES``.
Scoring reads every whole text once.

Defined results: a null or empty text has no words and gets the score of the empty set; labels
that are null, or of no document, are left out, repeated ones merged (worst
grade); without labels every score is zero and the thresholds are the initial ones; repeated rows are scored
each; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import shipped

#: Bounds of the fit.
SAMPLE, LEAST_DOCS, MAX_FEATURES = 20_000, 3, 100_000
SCREEN = 5.0
DIMS = 1 << 24
EPOCHS, BATCH, RATE, RIDGE = 30, 512, 0.15, 1e-4
#: A document is kept if its probability of the top grade reaches this.
KEEP_TAIL = 0.5
#: Words whose features a worker keeps.
CACHED_WORDS = 500_000
SEED = 29

_PARTS = re.compile(rb"^([^0-9A-Za-z\x80-\xff]*)(.*?)([^0-9A-Za-z\x80-\xff]*)$", re.S)


def hashed(name: bytes) -> int:
    import xxhash

    return xxhash.xxh32_intdigest(name, SEED) % DIMS


def word_features(word: bytes) -> tuple[int, ...]:
    """Hashed features of one word: its bare form, and shapes where they are unusual."""
    head, core, tail = _PARTS.match(word).groups()
    names = [b"w:" + core.lower()] if core else []
    if len(core) > 1 and core.isupper():
        names.append(b"s:upper")
    if head:
        names.append(b"h:" + head[:4])
    if len(tail) > 1 or tail not in (b"", b".", b","):
        names.append(b"t:" + tail[:4])
    if len(core) > 24:
        names.append(b"s:long")
    return tuple(map(hashed, names))


class WordTable:
    """Features of words met so far, restricted to ``known`` if given."""

    def __init__(self, known: dict[int, int] | None = None) -> None:
        self.known, self.table = known, {}

    def _own(self, name: bytes) -> tuple[int, ...]:
        """A feature of the whole text."""
        if name not in self.table:
            f = hashed(name)
            self.table[name] = (f,) if self.known is None else (self.known[f],) if f in self.known else ()
        return self.table[name]

    def document(self, text: bytes | None) -> set[int]:
        text = text or b""
        said = text.split()
        words = set(said)
        table = self.table
        if len(table) > CACHED_WORDS:
            table.clear()
        for w in words.difference(table):
            found = word_features(w)
            table[w] = found if self.known is None else tuple(self.known[f] for f in found if f in self.known)
        out = set().union(*map(table.__getitem__, words))
        lines = text.split(b"\n")
        size = len(said).bit_length()
        out.update(self._own(b" words %d %d" % (size, 10 * len(words) // max(1, len(said)))))
        out.update(self._own(b" lines %d" % (10 * len(set(lines)) // len(lines))))
        out.update(self._own(b" size %d" % size))
        return out


@dataclass
class OrdinalModel:
    features: np.ndarray
    weights: np.ndarray
    thresholds: np.ndarray

    def tails(self, scores: np.ndarray) -> np.ndarray:
        """P(grade > k) for each threshold k, a column each."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - scores[:, None], -50, 50)))


def screened(rows: list[np.ndarray], grades: np.ndarray, n_grades: int) -> np.ndarray:
    """Features that go with the grade: some threshold is passed more or less often than by chance."""
    names, inverse = np.unique(np.concatenate(rows), return_inverse=True)
    owner = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    n = np.bincount(inverse, minlength=len(names))
    far = np.zeros(len(names))
    for k in range(n_grades - 1):
        above = (grades > k).astype(float)
        share = above.mean()
        spread = np.sqrt(np.maximum(n * share * (1 - share), 1e-12))
        far = np.maximum(far, np.abs(np.bincount(inverse, above[owner], minlength=len(names)) - n * share) / spread)
    good = np.flatnonzero((far >= SCREEN) & (n >= LEAST_DOCS))
    return np.sort(names[good[np.argsort(-far[good], kind="stable")[:MAX_FEATURES]]])


def fit(rows: list[np.ndarray], grades: np.ndarray, n_grades: int = 3, epochs: int = EPOCHS, seed: int = SEED) -> OrdinalModel:
    """Adaptive gradient descent on the likelihood; ``rows`` are feature sets."""
    start = np.arange(n_grades - 1, dtype=float) - (n_grades - 2) / 2
    if not len(rows):
        return OrdinalModel(np.empty(0, np.int64), np.empty(0), start)
    names = screened(rows, grades, n_grades)
    place = [np.searchsorted(names, r) for r in rows]
    place = [p[(p < len(names)) & (names[np.minimum(p, len(names) - 1)] == r)] if len(names) else p[:0] for p, r in zip(place, rows, strict=True)]
    size = np.array([len(p) for p in place])
    flat, ends = np.concatenate(place) if len(place) else np.empty(0, np.int64), np.cumsum(size)
    w, gw = np.zeros(len(names)), np.full(len(names), 1e-6)
    t, gt = start.copy(), np.full(n_grades - 1, 1e-6)
    share = np.array([(grades > k).mean() for k in range(n_grades - 1)]).clip(1e-3, 1 - 1e-3)
    t = np.minimum.accumulate((np.log((1 - share) / share))[::-1])[::-1] if n_grades > 1 else t
    random = np.random.default_rng(seed)
    for _ in range(epochs):
        order = random.permutation(len(rows))
        for lo in range(0, len(order), BATCH):
            pick = order[lo : lo + BATCH]
            n = size[pick]
            index = np.repeat(ends[pick] - n, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            feature, owner = flat[index], np.repeat(np.arange(len(pick)), n)
            s = np.bincount(owner, w[feature], minlength=len(pick))
            y = grades[pick]
            # c[k] = P(grade <= k - 1), with 0 and 1 at the ends.
            c = np.zeros((len(pick), n_grades + 1))
            c[:, 1:-1] = 1 / (1 + np.exp(np.clip(s[:, None] - t[None, :], -50, 50)))
            c[:, -1] = 1
            row = np.arange(len(pick))
            hi, lo_ = c[row, y + 1], c[row, y]
            p = np.maximum(hi - lo_, 1e-9)
            # d log p / d s = -(hi (1 - hi) - lo (1 - lo)) / p.
            ds = -(hi * (1 - hi) - lo_ * (1 - lo_)) / p
            dt = np.zeros(n_grades - 1)
            for k in range(n_grades - 1):
                dens = c[:, k + 1] * (1 - c[:, k + 1]) / p
                dt[k] = dens[y == k].sum() - dens[y == k + 1].sum()
            g = np.bincount(feature, ds[owner], minlength=len(w)) / len(pick) - RIDGE * w
            gw += g * g
            w += RATE * g / np.sqrt(gw)
            dt /= len(pick)
            gt += dt * dt
            t = np.maximum.accumulate(t + RATE * dt / np.sqrt(gt))
    used = np.flatnonzero(w)
    return OrdinalModel(names[used], w[used], t)


def graded(labels: DataFrame) -> DataFrame:
    """``doc_id, grade``: 0 toxic, 1 poor, 2 good; the worst of repeated labels."""
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 0, 1).when(F.col("quality") == 1, 2)
    return labels.select("doc_id", grade.alias("grade")).where("doc_id is not null and grade is not null").groupBy("doc_id").agg(F.min("grade").alias("grade"))


def training_rows(docs: DataFrame, grades: DataFrame, sample: int = SAMPLE) -> tuple[list[np.ndarray], np.ndarray]:
    """Feature sets and grades of the sample; texts stay on the executors."""
    taken = grades.orderBy(F.xxhash64("doc_id", F.lit(SEED)), "doc_id").limit(sample)
    rows = docs.select("doc_id", F.col("text").cast("binary").alias("text")).join(F.broadcast(taken), "doc_id").select("doc_id", "grade", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = WordTable()
        for batch in batches:
            sets = [np.array(sorted(table.document(x.as_py())), "<i4").tobytes() for x in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("grade"), pa.array(sets, pa.binary())], ["doc_id", "grade", "features"])

    got = shipped(rows).mapInArrow(run, "doc_id long, grade int, features binary").dropDuplicates(["doc_id"]).orderBy("doc_id").collect()
    return [np.frombuffer(r["features"], "<i4").astype(np.int64) for r in got], np.array([r["grade"] for r in got], np.int64)


def score(docs: DataFrame, model: OrdinalModel, keep: tuple[str, ...] = ("doc_id",), text: str = "text", keep_tail: float = KEEP_TAIL) -> DataFrame:
    """``keep``, score, P(grade >= 1), P(grade >= 2), expected grade, most likely grade and the verdict of each whole text."""
    rows = docs.select(*keep, F.col(text).cast("binary").alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = WordTable({int(f): i for i, f in enumerate(model.features)})
        for batch in batches:
            s = np.array([model.weights[list(own)].sum() if (own := table.document(x.as_py())) else 0.0 for x in batch.column(len(keep))])
            tail = model.tails(s.reshape(-1))
            best = np.argmax(np.concatenate((1 - tail[:, :1], tail[:, :1] - tail[:, 1:], tail[:, 1:]), axis=1), axis=1)
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[: len(keep)], pa.array(s), pa.array(tail[:, 0]), pa.array(tail[:, 1]), pa.array(tail.sum(axis=1)), pa.array(best.astype(np.int64)), pa.array(tail[:, 1] >= keep_tail)],
                [*keep, "score", "p_decent", "p_good", "expected_grade", "grade", "kept"],
            )

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*keep).schema), "score double, p_decent double, p_good double, expected_grade double, grade long, kept boolean"])
    return shipped(rows).mapInArrow(run, schema)


def grade_documents(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """Fit on the labelled sample, score every document."""
    return score(docs, fit(*training_rows(docs, graded(labels), sample)))
