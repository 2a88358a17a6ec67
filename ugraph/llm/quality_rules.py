"""Quality rules with an isolation forest on their statistics.

Base rules reject texts with fewer than 50 words, or of which more than half the words lie in repeated three-word
windows. On rates made from the rule statistics an isolation forest is grown over random splits; documents with short
mean paths are anomalies. Junk mostly shows in one statistic, which the mean over trees of all of them would drown, so
each rate has TREES trees of its own, and a row's score is the greatest of its rates' scores. Junk comes in dense
clusters, which hide from a forest grown on everything, so the forest grows on a bounded sample of rows labelled good
(SAMPLE rows of least hash; of all rows where none is labelled good), and each split is drawn from the whole range
which the rate can take, not from the range of the node's rows. Before that a rate is bounded: its distance from the
sample's median, in units of the sample's spread, is mapped into (-1, 1). Median and spread are ranks of the sample, so
no single row, however extreme, moves the splits, and rows which the base rules reject have no say in them. The
threshold is calibrated on all labelled rows that pass the base rules: of the thresholds which reject at most
MAX_CLEAN_LOSS of the rows labelled good, those which reject most of the others, and the middle of these.

Defined cases: null text has no words; rows of equal or null doc_id are judged each on their own; a doc_id labelled
more than once counts with its highest label; with no labelled rows of both kinds the forest rejects nothing; extra
columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import least_hashed, map_arrow, materialise, slices

MIN_WORDS, REPEAT_PERCENT = 50, 50
#: Trees of each rate, rows of each tree, greatest depth, rows of the sample.
TREES, PER_TREE, DEPTH, SAMPLE, SEED = 12, 256, 10, 25_600, 17
SHRINK = 50
#: The rates, by which the next two tables go.
RATES = ["symbols a word", "capitals a character", "marks a word", "digits a character", "repeated lines a line", "repeated words a word", "logarithm of different words by that of words", "characters a word", "lines a word"]
#: The sample's spread lies between these two quantiles; a rate's unit is at least its entry in LEAST_UNIT.
SPREAD = (0.01, 0.99)
#: By rate: the least unit, and the greatest value that the rate can take.
LEAST_UNIT = np.array([0.05, 0.01, 0.05, 0.05, 0.05, 0.2, 0.1, 0.5, 0.05])
MOST = np.array([np.inf, 1.0, np.inf, 1.0, 1.0, 1.0, 1.0, np.inf, 1.0])
#: Share of the rows labelled good that the threshold may reject.
MAX_CLEAN_LOSS = 0.001
#: Scores are held in this many equal bins for the calibration.
BINS = 4096

BLANKS = " \t\n\r\x0b\x0c"
SYMBOLS = b"#*$%&|<>"
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
MORE = ["n_upper", "n_digits", "n_marks", "n_lines", "n_distinct"]
STATS = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS + MORE)

_UPPER = bytes(range(65, 91))
_DIGITS = bytes(range(48, 58))
_MARKS = b"!?;:()[]{}=+/\\@^~`_\"'"


def repeated_words(words: list[bytes]) -> tuple[int, int]:
    """Words covered by three-word windows found twice or more, and the number of different words."""
    known: dict[bytes, int] = {}
    ids = np.array([known.setdefault(w, len(known)) for w in words], dtype=np.int64)
    m = len(known)
    if len(ids) < 4:
        return 0, m
    pairs = ids[:-2] * m + ids[1:-1]
    if m > 1_000_000:
        pairs = np.unique(pairs, return_inverse=True)[1]
    keys = pairs * m + ids[2:]
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    if not same.any():
        return 0, m
    twice = np.zeros(len(keys), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(len(ids), bool)
    for d in range(3):
        covered[d : d + len(keys)] |= twice
    return int(covered.sum()), m


def text_stats(text: str) -> tuple[int, ...]:
    data = text.encode("utf-8", "surrogatepass")
    words = data.split()
    lines = text.split("\n")
    full = [x for x in lines if x.strip(BLANKS)]
    repeats, distinct = repeated_words(words)

    def count(chars: bytes) -> int:
        return len(data) - len(data.translate(None, chars))

    return (
        len(words), len(text) - sum(text.count(c) for c in BLANKS), count(SYMBOLS), len(full) - len(set(full)), repeats,
        count(_UPPER), count(_DIGITS), count(_MARKS), len(full), distinct,
    )


def _stats(batches):
    names = ["doc_id", *COUNTS, *MORE]
    for batch in batches:
        for part in slices(batch, "text"):
            rows = np.array([text_stats(t or "") for t in part.column("text").to_pylist()], dtype=np.int64).reshape(-1, len(names) - 1)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array(np.ascontiguousarray(c)) for c in rows.T)], names=names)


def rule_stats(docs: DataFrame) -> DataFrame:
    """doc_id and the statistics of every text."""
    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), _stats, STATS)


def rates(counts: np.ndarray) -> np.ndarray:
    """The forest's features, as RATES names them. SHRINK words more than there are, all different and of five characters,
    keep short texts from looking odd for a single sign. A text's different words grow more slowly than its length, so that
    their logarithms are compared: a share would make long texts look odd."""
    c = dict(zip(COUNTS + MORE, counts.astype(np.float64).T, strict=True))
    words, chars, lines = c["n_words"] + SHRINK, c["word_chars"] + 5 * SHRINK, c["n_lines"] + SHRINK / 5
    return np.stack([
        c["n_symbols"] / words, c["n_upper"] / chars, c["n_marks"] / words, c["n_digits"] / chars, c["n_dup_lines"] / lines, c["n_repeat_words"] / words,
        np.log(c["n_distinct"] + SHRINK) / np.log(words), chars / words, c["n_lines"] / words,
    ], axis=1)


class Bounds:
    """Maps rates into (-1, 1): 0 is the sample's median, 0.5 is one unit above it."""

    def __init__(self, sample: np.ndarray):
        width = len(LEAST_UNIT)
        self.mid, self.unit = np.zeros(width), LEAST_UNIT
        if len(sample):
            self.mid = np.median(sample, axis=0)
            below, above = np.quantile(sample, SPREAD[0], axis=0, method="higher"), np.quantile(sample, SPREAD[1], axis=0, method="lower")
            self.unit = np.maximum(np.maximum(self.mid - below, above - self.mid), LEAST_UNIT)
        self.low = self(np.zeros(width))
        self.high = np.where(np.isinf(MOST), 1.0, self(np.where(np.isinf(MOST), 0.0, MOST)))

    def __call__(self, rows: np.ndarray) -> np.ndarray:
        off = rows - self.mid
        return off / (self.unit + np.abs(off))


class IsolationForest:
    """Trees of random splits, ``trees`` for each feature; a feature's score is 2 ** (-mean path length / expected length),
    near 1 for outliers, and a row's score the greatest of them."""

    def __init__(self, sample: np.ndarray, trees: int = TREES, per_tree: int = PER_TREE, depth: int = DEPTH, seed: int = SEED):
        rng = np.random.default_rng(seed)
        per_tree = min(per_tree, len(sample))
        self.bounds = Bounds(sample)
        low, high, sample = self.bounds.low, self.bounds.high, self.bounds(sample)
        self.expected = max(float(self._length(np.array([per_tree]))[0]), 1.0)
        self.depth = depth
        self.trees = []
        for f in range(sample.shape[1]):
            alone = np.arange(sample.shape[1]) == f
            self.trees.append([self._grow(sample[rng.permutation(len(sample))[:per_tree]], np.where(alone, low, 0), np.where(alone, high, 0), rng) for _ in range(trees)])

    @staticmethod
    def _length(n: np.ndarray) -> np.ndarray:
        """Mean depth of a failed search among n keys."""
        n = n.astype(np.float64)
        return np.where(n > 2, 2 * (np.log(np.maximum(n - 1, 1)) + np.euler_gamma) - 2 * (n - 1) / np.maximum(n, 1), np.where(n == 2, 1.0, 0.0))

    def _grow(self, rows: np.ndarray, low: np.ndarray, high: np.ndarray, rng) -> tuple[np.ndarray, ...]:
        feature, cut, left, right, length = [], [], [], [], []

        def node(rows, low, high, level):
            k = len(feature)
            for column, v in ((feature, 0), (cut, np.inf), (left, k), (right, k), (length, 0.0)):
                column.append(v)
            wide = np.flatnonzero(high > low)
            if level == self.depth or len(rows) < 2 or not len(wide):
                length[k] = level + float(self._length(np.array([len(rows)]))[0])
                return k
            f = int(rng.choice(wide))
            at = float(rng.uniform(low[f], high[f]))
            side = rows[:, f] < at
            feature[k], cut[k] = f, at
            below, above = high.copy(), low.copy()
            below[f] = above[f] = at
            left[k] = node(rows[side], low, below, level + 1)
            right[k] = node(rows[~side], above, high, level + 1)
            return k

        node(rows, low, high, 0)
        return tuple(np.array(x) for x in (feature, cut, left, right, length))

    def score(self, rows: np.ndarray) -> np.ndarray:
        rows = self.bounds(rows)
        most, every = np.zeros(len(rows)), np.arange(len(rows))
        for trees in self.trees:
            total = np.zeros(len(rows))
            for feature, cut, left, right, length in trees:
                at = np.zeros(len(rows), dtype=np.int64)
                for _ in range(self.depth):
                    at = np.where(rows[every, feature[at]] < cut[at], left[at], right[at])
                total += length[at]
            most = np.maximum(most, 2.0 ** (-total / len(trees) / self.expected))
        return most


def base_failed(n_words, n_repeat_words):
    return (n_words < MIN_WORDS) | (100 * n_repeat_words > REPEAT_PERCENT * n_words)


def _verdicts(forest: IsolationForest, threshold: float):
    def run(batches):
        for batch in batches:
            counts = np.stack([np.asarray(batch.column(c)) for c in COUNTS + MORE], axis=1)
            score = forest.score(rates(counts)) if len(counts) else np.zeros(0)
            failed = base_failed(counts[:, 0], counts[:, 4])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score), pa.array(failed), pa.array(~failed & (score < threshold))], names=[*batch.schema.names, "score", "base_failed", "kept"])

    return run


VERDICTS = STATS + ", score double, base_failed boolean, kept boolean"


def fit(stats: DataFrame, labels: DataFrame) -> tuple[IsolationForest, float]:
    """The forest from a sample of ``stats`` and the threshold from all rows with labels."""
    marks = labels.filter("quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("quality"))

    def sample(rows: DataFrame) -> np.ndarray:
        rows = rows.filter(~base_failed(F.col("n_words"), F.col("n_repeat_words")))
        return least_hashed(rows, SAMPLE, SEED, "doc_id", *COUNTS).select(*COUNTS, *MORE).toPandas().to_numpy(dtype=np.int64)

    rows = sample(stats.join(marks.filter("quality = 1"), "doc_id"))
    if not len(rows):
        rows = sample(stats)
    forest = IsolationForest(rates(rows))
    scored = map_arrow(stats, _verdicts(forest, 2.0), VERDICTS).filter("not base_failed").join(marks, "doc_id")
    bins = scored.groupBy(F.floor(F.col("score") * BINS).alias("bin"), (F.col("quality") == 1).alias("good")).count().collect()  # at most 2 x BINS rows
    good, bad = np.zeros(BINS + 1), np.zeros(BINS + 1)
    for r in bins:
        (good if r["good"] else bad)[min(int(r["bin"]), BINS)] += r["count"]
    if not good.sum() or not bad.sum():
        return forest, 2.0
    lost = np.cumsum(good[::-1])[::-1] / good.sum()
    caught = np.cumsum(bad[::-1])[::-1]
    allowed = np.flatnonzero(lost <= MAX_CLEAN_LOSS)
    if not len(allowed):
        return forest, 2.0
    alike = np.flatnonzero(caught == caught[allowed[0]])[-1]
    return forest, float(allowed[0] + alike) / 2 / BINS


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """op6: the statistics, base_failed and kept of every document."""
    stats = materialise(rule_stats(docs), "rule-stats")
    forest, threshold = fit(stats, labels)
    return map_arrow(stats, _verdicts(forest, threshold), VERDICTS)


def quality_digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    return judge(docs, labels).select("doc_id", *COUNTS, "base_failed", "kept", "score")


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without the rejected documents, with its own columns. The model comes from one pass over the texts;
    a second pass judges each row where it stands, so that no text is shuffled."""
    forest, threshold = fit(materialise(rule_stats(docs), "rule-stats"), labels)

    def run(batches):
        for batch in batches:
            for part in slices(batch.set_column(batch.schema.get_field_index("text"), "text", batch.column("text").cast(pa.string())), "text"):
                counts = np.array([text_stats(t or "") for t in part.column("text").to_pylist()], dtype=np.int64).reshape(-1, len(COUNTS + MORE))
                failed = base_failed(counts[:, 0], counts[:, 4])
                yield part.filter(pa.array(~failed & (forest.score(rates(counts)) < threshold)))

    return map_arrow(docs, run, docs.schema)
