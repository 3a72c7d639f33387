"""Toxic passages as maximal scoring segments of token log-odds.

Token weights are log-odds of toxic against other labelled documents, smoothed by a Dirichlet prior
of equal strength in each cell whose mean is the pooled rate, and shrunk by their standard error.  Tokens are words and their
first letters, hashed to a fixed number of cells, so the weights that every task gets have one size whatever the corpus.
A linear scan finds all maximal scoring segments of a text (those that no extension or cut improves),
each of which is a passage; runs of unweighted words lower a segment's score.
For a text without toxic passages the largest segment score follows an extreme-value law whose centre
grows with the logarithm of the length; its parameters come from labelled clean documents.
A segment is significant by its chance under that law, the chances of a text's significant segments are
combined, and a one-dimensional logistic fit turns the evidence into a score.

Fitting uses about `TRAINING_ROWS` labelled rows for the weights, `TUNING_ROWS` for the choice of a setting and
`CALIBRATION_ROWS` for the two calibrations, chosen by a hash of the id, or all if there are fewer.  All of
them have a remainder other than 0; weights for a row that tunes or calibrates come from the other fold
only, and of the settings in `GRID` the one with the least cross-validated log loss is taken.  Labels,
language, source and id are never inputs of a score.

Edge cases: too few labels of both kinds for a choice take the setting `USUAL`; a null or empty text, or one without words, has no segment and gets the score of no
evidence; a null id is scored and is not used for training; repeated labels of an id are all used; without
labels of both kinds every text gets the score 0.0; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import product
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzcount.sources.tables import cut, drop

CELLS = 1 << 19
STEMS = (4, 5, 6)  # leading letters that count as tokens beside the whole word
FOLDS = 2
#: Labelled rows that the weights, the setting and the calibrations are fitted on, about, by a hash of the id; 24 bytes a row are broadcast.
TRAINING_ROWS, TUNING_ROWS, CALIBRATION_ROWS = 200_000, 3_000, 20_000
SIGNIFICANT = 0.05
TRIM = 0.03
WORDS_CACHED = 300_000


class Setting(NamedTuple):
    """What is chosen among the training folds."""

    prior: float  # tokens of prior in each cell, dealt over the kinds by their sizes
    least_z: float  # standard errors below which a token says nothing
    drift: float  # what a word without evidence takes off a segment
    stems: bool  # whether first letters count beside whole words
    fading: bool  # whether the n-th time a word weighs an n-th


GRID = [Setting(*x) for x in product((0.5, 2.0), (2.0, 3.0, 4.0), (0.1, 0.2, 0.4), (False, True), (False, True))]
USUAL = Setting(2.0, 3.0, 0.2, True, True)

_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def cells_of(word: str) -> tuple[int, ...]:
    """The cells of a word's tokens: the word itself and its first letters (cell 0 where it has no more)."""
    return (_cell(word), *(_cell("^" + word[:n]) if len(word) > n else 0 for n in STEMS))


def _cell(token: str) -> int:
    return 1 + zlib.crc32(token.encode()) % (CELLS - 1)


class Tally:
    """In how many texts each token stands; remembers the cells of words while they fit."""

    def __init__(self) -> None:
        self.known: dict[str, tuple[int, ...]] = {}

    def add(self, text: str, sums: np.ndarray) -> None:
        words = set(words_of(text))
        if len(self.known) > WORDS_CACHED:
            self.known.clear()
        for word in [w for w in words if w not in self.known]:
            self.known[word] = cells_of(word)
        if words:
            np.add.at(sums, np.array([self.known[w] for w in words]), 1)


def faded(words: list[str], scores: np.ndarray) -> np.ndarray:
    """`scores` with those above zero divided by how often their word has stood there."""
    seen: dict[str, int] = defaultdict(int)
    for i in np.flatnonzero(scores > 0).tolist():
        seen[words[i]] += 1
        scores[i] /= seen[words[i]]
    return scores


class Weigher:
    """The weight of each word of a text: of its tokens the one that speaks most for a toxic passage, less the drift."""

    def __init__(self, weights: np.ndarray, setting: Setting):
        self.weights, self.setting, self.known = weights, setting, {}

    def of(self, text: str) -> np.ndarray:
        words = words_of(text)
        found = list(map(self.known.get, words))
        if None in found:
            if len(self.known) > WORDS_CACHED:
                self.known.clear()
            tokens = slice(None) if self.setting.stems else slice(1)
            for i, weight in enumerate(found):
                if weight is None:
                    found[i] = self.known[words[i]] = float(self.weights[list(cells_of(words[i])[tokens])].max()) - self.setting.drift
        scores = np.array(found, np.float64)
        return faded(words, scores) if self.setting.fading else scores


class Trials:
    """What `Weigher` gives under many settings, for the rows that one is chosen by."""

    def __init__(self, counts: np.ndarray, settings: list[Setting]):
        self.settings, kinds = settings, sorted({(s.prior, s.least_z) for s in settings})
        self.place = {kind: i for i, kind in enumerate(kinds)}
        self.weights = np.stack([log_odds(counts[1], counts[0], *kind) for kind in kinds])
        self.known: dict[str, np.ndarray] = {}

    def of(self, text: str) -> Iterator[np.ndarray]:
        words = words_of(text)
        if len(self.known) > WORDS_CACHED // 10:
            self.known.clear()
        for word in {w for w in words if w not in self.known}:
            each = self.weights[:, list(cells_of(word))]
            self.known[word] = np.stack([each[:, 0], each.max(1)])
        all_of = np.array([self.known[w] for w in words]).reshape(len(words), 2, len(self.weights))
        for s in self.settings:
            scores = all_of[:, int(s.stems), self.place[s.prior, s.least_z]].astype(np.float64) - s.drift
            yield faded(words, scores) if s.fading else scores


def log_odds(toxic: np.ndarray, clean: np.ndarray, prior: float, least_z: float) -> np.ndarray:
    """Weight of each cell: the log-odds less their standard error where clear."""
    share = (toxic.sum() + 1) / (toxic.sum() + clean.sum() + 2)
    a, b = toxic + prior * share, clean + prior * (1 - share)
    odds = np.log(a / share) - np.log(b / (1 - share))
    error = np.sqrt(1 / a + 1 / b)
    sure = np.sign(odds) * np.maximum(0.0, np.abs(odds) - error)
    weights = np.where(np.abs(odds) > least_z * error, sure, 0.0).astype(np.float32)
    weights[0] = -np.inf
    return weights


def segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments as (start, end, score), by one pass over runs of equal sign."""
    if not len(scores):
        return []
    up = scores > 0
    if not up.any():
        return []
    starts = np.flatnonzero(np.r_[True, up[1:] != up[:-1]])
    sums = np.add.reduceat(scores.astype(np.float64), starts)
    ends = np.r_[starts[1:], len(scores)]
    kept: list[list] = []  # [total before, total after, start, end]
    link: list[int] = []  # of each kept segment the nearest one to its left with a smaller total before
    total = 0.0
    for start, end, value, rising in zip(starts.tolist(), ends.tolist(), sums.tolist(), up[starts].tolist(), strict=True):
        before, total = total, total + value
        if not rising:
            continue
        new = [before, total, start, end]
        while True:
            j = len(kept) - 1
            while j >= 0 and kept[j][0] >= new[0]:
                j = link[j]
            if j < 0 or kept[j][1] >= new[1]:
                break
            new = [kept[j][0], new[1], kept[j][2], new[3]]
            del kept[j:], link[j:]
        kept.append(new)
        link.append(j)
    return [(s, e, after - before) for before, after, s, e in kept]


@dataclass(frozen=True)
class Calibration:
    """The null law of the largest segment score and the logistic map of the evidence."""

    rate: float
    scale: float
    slope: float
    offset: float

    def chance(self, score: float, words: int) -> float:
        """Probability that a clean text of so many words has a segment of this score or more."""
        expected = self.scale * max(words, 1) * math.exp(-min(self.rate * score, 700.0))
        return -math.expm1(-expected)

    def evidence(self, found: list[tuple[int, int, float]], words: int) -> float:
        """Minus log chance of the strongest segment, plus what other significant ones add to it."""
        logs = sorted((-math.log(max(self.chance(s, words), 1e-300)) for _, _, s in found), reverse=True)
        if not logs:
            return 0.0
        return math.log1p(logs[0] + sum(x for x in logs[1:] if x > -math.log(SIGNIFICANT)))

    def score(self, evidence: float) -> float:
        return 1 / (1 + math.exp(-max(-500.0, min(500.0, self.slope * evidence + self.offset))))


@dataclass(frozen=True)
class Model:
    weights: np.ndarray
    calibration: Calibration | None
    setting: Setting = USUAL

    def judge(self, scores: np.ndarray) -> tuple[float, list[tuple[int, int, float, float]]]:
        """(score, significant passages as (first word, end, segment score, chance))."""
        if self.calibration is None:
            return 0.0, []
        found = segments(scores)
        score = self.calibration.score(self.calibration.evidence(found, len(scores)))
        told = [(s, e, v, self.calibration.chance(v, len(scores))) for s, e, v in found]
        return score, [x for x in told if x[3] <= SIGNIFICANT]


def fit_null(best: np.ndarray, words: np.ndarray) -> tuple[float, float]:
    """Rate and scale of the extreme-value law: the maximum-likelihood fit, the length entering the centre."""
    kept = best <= np.quantile(best, 1 - TRIM)  # labels err
    best, words = best[kept], words[kept]
    rates, fits = np.geomspace(0.05, 5.0, 60), []
    for rate in rates:
        seen = words * np.exp(-rate * best)
        scale = len(best) / max(seen.sum(), 1e-300)
        fits.append((np.log(scale * rate * np.maximum(words, 1)) - rate * best - scale * seen).sum())
    rate = float(rates[int(np.argmax(fits))])
    return rate, float(len(best) / max((words * np.exp(-rate * best)).sum(), 1e-300))


def fit_logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset by Newton steps with a weak pull towards zero slope."""
    features, weight = np.c_[x, np.ones_like(x)], np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(features @ weight, -30, 30)))
        gradient = features.T @ (p - y) + 1e-3 * weight * [1, 0]
        hessian = (features * (p * (1 - p))[:, None]).T @ features + np.diag([1e-3, 1e-6])
        weight = weight - np.clip(np.linalg.solve(hessian, gradient), -2, 2)
    return float(weight[0]), float(weight[1])


def cross_loss(part: np.ndarray, y: np.ndarray, x: np.ndarray) -> float:
    """Mean log loss of each fold under the logistic fit of the others; infinite if a fold lacks a kind."""
    total = 0.0
    for i in range(FOLDS):
        own, other = part == i, part != i
        if len({*y[own]}) < 2 or len({*y[other]}) < 2:
            return math.inf
        slope, offset = fit_logistic(x[other], y[other])
        p = np.clip(1 / (1 + np.exp(-np.clip(slope * x[own] + offset, -30, 30))), 1e-9, 1 - 1e-9)
        total -= (y[own] * np.log(p) + (1 - y[own]) * np.log(1 - p)).sum()
    return float(total / len(y))


def fold(id_col: str) -> Column:
    """What the contract calls the remainder: crc32 of the id as text, modulo 5."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(5))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Weights and calibration from the rows whose remainder is not 0."""
    told = labels.where("toxic IS NOT NULL").select(F.col(id_col).alias("__id"), F.col("toxic").cast("int").alias("toxic"))
    told = told.withColumn("fold", fold("__id")).where("fold <> 0")
    texts = docs.select(F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    there = max(1, told.count())

    def sample(most: int) -> DataFrame:
        """The texts of about `most` labelled rows, or of all if there are no more; the labels are broadcast."""
        below = int(2**63 * min(1.0, most / there) * 2) - 2**63 - 1
        return texts.join(F.broadcast(told.where(F.xxhash64("__id") <= below)), "__id")

    rows = sample(TRAINING_ROWS)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally, sums = Tally(), np.zeros((2, FOLDS, CELLS), np.int64)
        for batch in batches:
            for toxic, part, text in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                tally.add(text, sums[int(toxic == 1), part % FOLDS])
        sums[:, :, 0] = 0
        toxic, part, cell = np.nonzero(sums)
        yield pa.RecordBatch.from_arrays([pa.array(toxic.astype(np.int32)), pa.array(part.astype(np.int32)), pa.array(cell.astype(np.int32)), pa.array(sums[toxic, part, cell])], names=["toxic", "part", "cell", "n"])

    counted = rows.select("toxic", F.col("fold").cast("int").alias("fold"), "text").mapInArrow(count, "toxic int, part int, cell int, n bigint")
    found = counted.groupBy("toxic", "part", "cell").agg(F.sum("n").alias("n")).toArrow()  # 2 * FOLDS * CELLS rows at most
    sums = np.zeros((2, FOLDS, CELLS))
    toxic, part, cell, n = (found.column(i).to_numpy() for i in range(4))
    sums[toxic, part, cell] = n
    if not sums[1].sum() or not sums[0].sum():
        return Model(np.zeros(CELLS, np.float32), None)
    others = [sums.sum(1) - sums[:, i] for i in range(FOLDS)]
    spark = docs.sparkSession

    def tried(most: int, settings: list[Setting]) -> tuple[list[tuple[float, float]], list[tuple[np.ndarray, ...]]]:
        """Of each setting the law of the largest segment score, and (part, toxic, evidence) of about `most` rows."""
        shared = spark.sparkContext.broadcast([x.astype(np.float32) for x in others])  # 4 MB a fold

        def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            trials = [Trials(x, settings) for x in shared.value]
            for batch in batches:
                for at in range(0, batch.num_rows, 100):
                    out = []
                    for toxic, part, text in zip(*(batch.slice(at, 100).column(i).to_pylist() for i in range(3)), strict=True):
                        for i, scores in enumerate(trials[part % FOLDS].of(text)):
                            out.append((i, part % FOLDS, toxic, len(scores), sorted((v for _, _, v in segments(scores)), reverse=True)))
                    columns = list(zip(*out, strict=True)) or [()] * 5
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (*[pa.int32()] * 3, pa.int64(), pa.list_(pa.float64())), strict=True)], names=["setting", "part", "toxic", "words", "found"])

        seen = cut(sample(most).select("toxic", F.col("fold").cast("int").alias("fold"), "text").mapInArrow(look, "setting int, part int, toxic int, words bigint, found array<double>"))
        tops = seen.where("toxic = 0 AND words > 0 AND size(found) > 0").select("setting", "words", F.col("found")[0].alias("top")).toArrow()
        setting, words, top = (tops.column(i).to_numpy() for i in range(3))
        laws = []
        for i in range(len(settings)):
            mine = setting == i
            laws.append(fit_null(top[mine], words[mine].astype(float)) if mine.sum() > 10 else (1.0, 0.01))

        def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            known = [Calibration(*law, 0.0, 0.0) for law in laws]
            for batch in batches:
                setting, words, found = (batch.column(i).to_pylist() for i in (0, 3, 4))
                x = [known[i].evidence([(0, 0, v) for v in f], n) for i, n, f in zip(setting, words, found, strict=True)]
                yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(x, pa.float64())], names=["setting", "part", "toxic", "x"])

        told = seen.mapInArrow(weigh, "setting int, part int, toxic int, x double").toArrow()  # settings x `most` rows or so
        drop(seen)
        setting, part, toxic, x = (told.column(i).to_numpy() for i in range(4))
        return laws, [(part[setting == i], (toxic[setting == i] == 1).astype(float), x[setting == i]) for i in range(len(settings))]

    losses = [cross_loss(*found) for found in tried(TUNING_ROWS, GRID)[1]]
    setting = GRID[int(np.argmin(losses))] if np.isfinite(min(losses)) else USUAL
    (law,), ((_, y, x),) = tried(CALIBRATION_ROWS, [setting])
    return Model(log_odds(sums[1].sum(0), sums[0].sum(0), setting.prior, setting.least_z), Calibration(*law, *fit_logistic(x, y)), setting)


SCORED = "doc_id bigint, score double, segments array<struct<first_word:int,end_word:int,score:double,chance:double>>"


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score and the significant passages of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2 MB of weights
    passage = pa.struct([("first_word", pa.int32()), ("end_word", pa.int32()), ("score", pa.float64()), ("chance", pa.float64())])

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        weigher = Weigher(known.weights, known.setting)
        for batch in batches:
            told = [known.judge(weigher.of(text.as_py())) for text in batch.column(1)]
            found = [[{"first_word": s, "end_word": e, "score": v, "chance": c} for s, e, v, c in t[1]] for t in told]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t[0] for t in told], pa.float64()), pa.array(found, pa.list_(passage))], names=["doc_id", "score", "segments"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).mapInArrow(judge, SCORED)


def drop_toxic(docs: DataFrame, model: Model, threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """`docs` without the rows that score `threshold` or more; all columns stay as they are."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text_col)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        weigher = Weigher(known.weights, known.setting)
        for batch in batches:
            scores = [known.judge(weigher.of(text.as_py() or ""))[0] for text in batch.column(at)]
            yield batch.filter(pa.array([s < threshold for s in scores], pa.bool_()))

    return docs.mapInArrow(keep, docs.schema)
