"""Toxicity by compression distance.

Zstandard trains two dictionaries, and the difference of a window's two compressed lengths, with the ordinary one less with the toxic
one, says which class it is like. Windows run over the whole of a text, one for each word (long words, and scripts without spaces, are
cut into windows of at most WIDE bytes); a frame that both dictionaries end with stands around each, so that the lengths of short
windows differ at all. Windows of two and three words told less on held-out labels: more of what they hold is ordinary.

A toxic text is mostly ordinary, so what zstandard trains on is narrowed in rounds. The first toxic dictionary comes from whole toxic
texts, the first ordinary one from whole ordinary texts. A round compares all windows of the training texts, each with dictionaries
from the other folds, finds the least difference that toxic texts have NEED times as often, and hands the windows from there on
to the next round: those of toxic texts train the next toxic dictionary, those of ordinary texts are put before the next ordinary one.
The thresholds' counts in a text and its length make the score by a logistic curve, fitted on a round's cross-fitted differences; the
round whose curve has the least loss is kept.

Fitting reads labelled rows up to bounds for each class (SAMPLE, SAMPLE_BYTES), those with the least hash of their id; scoring
reads every window of every text.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass, field

import numpy as np
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nzspan.session import ship

from . import common

#: Labelled texts of each class, and bytes of them, that a fit reads at most.
SAMPLE, SAMPLE_BYTES = 3000, 64 << 20
#: Folds of the training texts; how much more often toxic texts must have a difference, by round; bytes of the dictionaries that follow.
FOLDS, NEED, SIZES = 3, (1.5, 2.5, 4.0, 5.0), (16384, 8192, 4096, 4096)
#: Bytes of the first dictionaries and of the samples they are trained on; zstandard's segment and match sizes in training.
FIRST, SAMPLED, SEGMENT, SEGMENT_NEXT, MATCH = 32768, 128, 128, 32, 6
#: Windows a threshold needs; widest window in bytes; largest difference; thresholds counted in a text.
LEAST, WIDE, WIDEST = 50, 48, 20
THRESHOLDS = range(2, 11)
#: Text around each window.
FRAME = b"0123456789abcdef"
#: Remembered windows of a worker; places that mark runs of windows as seen.
MEMORY, SEEN = 150_000, 1 << 24


def windows_of(text: str | None) -> list[bytes]:
    """The windows of a text: its words between spaces, long ones in pieces."""
    out = []
    for w in common.byte_words(text):
        if len(w) <= WIDE:
            out.append(b" " + w + b" ")
        else:
            out += [b" " + w[k : k + WIDE] + b" " for k in range(0, len(w), WIDE)]
    return out


def trained(samples: list[bytes], size: int, segment: int) -> bytes:
    """Dictionary content by zstandard's trainer, of a smaller size where samples are few; the samples themselves where they are too few to train on."""
    samples = [x for x in samples if len(x) >= 8]
    while size >= 256:
        try:
            return zstandard.train_dictionary(size, samples, k=min(segment, size // 4), d=MATCH).as_bytes()
        except zstandard.ZstdError:
            size //= 2
    return b"".join(samples)[-FIRST:]


def pieces(texts: list[list[bytes]]) -> list[bytes]:
    """Whole texts, given by their windows, cut into samples."""
    flat = [b"".join(w[:-1] for w in t) + b" " for t in texts if t]
    return [t[k : k + SAMPLED] for t in flat for k in range(0, len(t), SAMPLED)]


def compressed_lengths(content: bytes):
    """A function from windows to their compressed lengths with a dictionary of this content."""
    p = zstandard.ZstdCompressionParameters.from_level(3, min_match=3, write_content_size=False, write_checksum=False, write_dict_id=False)
    z = zstandard.ZstdCompressor(dict_data=zstandard.ZstdCompressionDict(content + FRAME, dict_type=zstandard.DICT_TYPE_RAWCONTENT), compression_params=p)

    def lengths(windows: list[bytes]) -> np.ndarray:
        if not windows:
            return np.zeros(0, np.int64)
        size = np.fromiter(map(len, windows), np.uint64, len(windows))
        start = np.cumsum(size + np.uint64(len(FRAME))) - size - np.uint64(len(FRAME))
        spans = np.stack([start, size + np.uint64(2 * len(FRAME))], 1).tobytes()
        found = z.multi_compress_to_buffer(zstandard.BufferWithSegments(FRAME + FRAME.join(windows) + FRAME, spans), threads=0)
        return np.fromiter(map(len, found), np.int64, len(windows))

    return lengths


def in_turns(lengths, windows: list[bytes], most: int = 20_000) -> np.ndarray:
    return np.concatenate([lengths(windows[lo : lo + most]) for lo in range(0, max(1, len(windows)), most)])


@dataclass
class Model:
    toxic: bytes
    ordinary: bytes
    weights: np.ndarray  # of the features

    def differ(self):
        """A function from the windows of texts to the differences of each, from -WIDEST to WIDEST; it remembers windows."""
        ours, theirs, memo = compressed_lengths(self.toxic), compressed_lengths(self.ordinary), {}

        def differences(texts: list[list[bytes]]) -> list[np.ndarray]:
            if len(memo) >= MEMORY:
                memo.clear()
            missing = list({w for t in texts for w in t if w not in memo})
            memo.update(zip(missing, np.clip(in_turns(theirs, missing) - in_turns(ours, missing), -WIDEST, WIDEST).tolist(), strict=True))
            return [np.fromiter(map(memo.__getitem__, t), np.int64, len(t)) for t in texts]

        return differences

    def score(self, features: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(features @ self.weights, -40, 40)))


def features(differences: np.ndarray) -> np.ndarray:
    """One, and the logarithms of the number of windows and of those at each threshold or above."""
    told = np.bincount(differences + WIDEST, minlength=2 * WIDEST + 1)[::-1].cumsum()[::-1]
    return np.concatenate([[1.0, math.log1p(len(differences))], np.log1p(told[[WIDEST + t for t in THRESHOLDS]])])


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.01) -> np.ndarray:
    """Weights of a ridge logistic regression by Newton steps."""
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1.0 / (1.0 + np.exp(-np.clip(x @ w, -40, 40)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w)), x.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def one_of_copies(texts: list[list[bytes]]) -> list[list[bytes]]:
    """Texts of which at least half the runs of five windows are in none before."""
    seen = bytearray(SEEN)  # marks by hash: a few runs count as seen that were not
    out = []
    for t in texts:
        runs = {zlib.crc32(b"".join(t[k : k + 5])) % SEEN for k in range(max(1, len(t) - 4))}
        if 2 * sum(seen[r] for r in runs) <= len(runs):
            out.append(t)
        for r in runs:
            seen[r] = 1
    return out


@dataclass
class Class:
    """The training texts of one class as numbers of windows, by fold."""

    texts: list[list[bytes]]
    folds: int
    numbers: list[np.ndarray] = field(default_factory=list)

    def number(self, index: dict[bytes, int]) -> None:
        self.numbers = [np.array([index.setdefault(w, len(index)) for w in t], np.int64) for t in self.texts]

    def fold(self, k: int) -> list[int]:
        return [i for i in range(len(self.texts)) if i % self.folds == k]

    def others(self, k: int | None) -> list[list[bytes]]:
        """Texts outside fold k; all of them for None, or where there is one fold only."""
        return [t for i, t in enumerate(self.texts) if k is None or self.folds == 1 or i % self.folds != k]

    def counts(self, k: int, n: int) -> np.ndarray:
        own = [self.numbers[i] for i in self.fold(k)]
        return np.bincount(np.concatenate(own) if own else np.zeros(0, np.int64), minlength=n)


def least_difference(toxic: np.ndarray, ordinary: np.ndarray, need: float) -> int:
    """The least difference above 0 that, or more than it, toxic texts have `need` times as often; the most telling one if there is none.

    Both are counts of the differences from -WIDEST to WIDEST.
    """
    up = lambda c: c[::-1].cumsum()[::-1].astype(float)
    above, below = up(toxic), up(ordinary)
    ratio = (above + 0.5) / (above[0] + 1) / ((below + 0.5) / (below[0] + 1))
    enough = above >= min(LEAST, max(1.0, above[WIDEST + 1] / 2))
    ratio = np.where(enough, ratio, 0.0)[WIDEST + 1 :]
    good = np.flatnonzero(ratio >= need)
    return int(good[0] if len(good) else np.argmax(ratio)) + 1


def fit(toxic: list[str], ordinary: list[str], need: tuple[float, ...] = NEED, sizes: tuple[int, ...] = SIZES) -> Model:
    """A model from texts of either class; one that scores all texts by the share of toxic ones if a class is empty."""
    none = np.zeros(2 + len(THRESHOLDS))
    same: dict[bytes, bytes] = {}  # every window is held once
    groups = [one_of_copies([[same.setdefault(w, w) for w in windows_of(t)] for t in dict.fromkeys(texts)]) for texts in (toxic, ordinary)]
    if not all(any(g) for g in groups):
        none[0] = math.log((len(toxic) + 0.5) / (len(ordinary) + 0.5)) if toxic or ordinary else -1.0
        return Model(b"", b"", none)
    folds = FOLDS if min(map(len, groups)) >= 2 * FOLDS else 1
    ours, theirs = (Class(g, folds) for g in groups)
    index: dict[bytes, int] = {}
    for c in (ours, theirs):
        c.number(index)
    words, n = list(index), len(index)
    turns = [*range(folds), None]  # None: with all folds, for scoring
    counted = [[c.counts(k, n) for k in range(folds)] for c in (ours, theirs)]
    base = {k: trained(pieces(theirs.others(k)), FIRST, SEGMENT) for k in turns}
    dictionaries = {k: (trained(pieces(ours.others(k)), FIRST, SEGMENT), base[k]) for k in turns}
    y = np.array([1.0] * len(ours.texts) + [0.0] * len(theirs.texts))
    rng, best, least_loss = np.random.default_rng(42), None, math.inf
    for r in range(len(need) + 1):
        apart = []
        for k in range(folds):
            near, far = (in_turns(compressed_lengths(content), words) for content in dictionaries[k])
            apart.append(np.clip(far - near, -WIDEST, WIDEST))
        x = np.array([features(apart[i % folds][t]) for c in (ours, theirs) for i, t in enumerate(c.numbers)])
        model = Model(*dictionaries[None], logistic(x, y))
        chance = np.clip(np.where(y > 0, model.score(x), 1.0 - model.score(x)), 1e-6, 1.0)
        loss = -sum(np.log(chance[y == v]).mean() for v in (0, 1))
        if loss < least_loss:
            best, least_loss = model, loss
        if r == len(need):
            break
        seen = [sum(np.bincount(apart[k] + WIDEST, weights=counts[k], minlength=2 * WIDEST + 1) for k in range(folds)) for counts in counted]
        least = least_difference(*seen, need[r])
        picked = [[np.where(apart[k] >= least, counts[k], 0) for k in range(folds)] for counts in counted]

        def samples(of: list[np.ndarray], k: int | None) -> list[bytes]:
            total = sum(c for j, c in enumerate(of) if k is None or folds == 1 or j != k)
            # the trainer goes through its samples by stretches, each of which should hold all kinds
            return [words[i] for i in rng.permutation(np.repeat(np.arange(n), total))]

        for k in turns:
            dictionaries[k] = trained(samples(picked[0], k), sizes[r], SEGMENT_NEXT), trained(samples(picked[1], k), sizes[r], SEGMENT_NEXT) + base[k]
    return best


def training_sample(documents: DataFrame, labels: DataFrame, sample: int = SAMPLE, most: int = SAMPLE_BYTES, folds: int = 5) -> tuple[list[str], list[str]]:
    """Texts of labelled rows outside the held-out fold, toxic and ordinary, up to `sample` texts and `most` bytes of each class."""
    chosen = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & (common.fold_bucket(F.col("doc_id"), folds) != 0))
    order = [F.xxhash64(F.lit(7), "doc_id"), "doc_id"]
    out = []
    for value in (1, 0):
        ids = chosen.where(F.col("toxic") == value).select("doc_id").distinct().orderBy(*order).limit(sample)
        texts = documents.select("doc_id", "text").join(F.broadcast(ids), "doc_id", "left_semi").where("text IS NOT NULL").orderBy(*order, "text").limit(sample)
        so_far = F.sum(F.octet_length("text")).over(Window.orderBy(*order, "text").rowsBetween(Window.unboundedPreceding, 0))  # over `sample` rows at most
        out.append([r["text"] for r in texts.withColumn("so_far", so_far).where(F.col("so_far") <= most).collect()])
    return out[0], out[1]


def fitted(documents: DataFrame, labels: DataFrame) -> Model:
    """The model of the labelled rows outside the held-out fold; what fitting held is given back, as the driver goes on."""
    model = fit(*training_sample(documents, labels))
    common.give_back()
    return model


def score_documents(documents: DataFrame, model: Model) -> DataFrame:
    """(row..., score, predicted) for every row of documents; all its columns stay, the two are new at the end."""
    ship(documents.sparkSession)
    schema = [f for f in documents.schema.fields if f.name not in ("score", "predicted")]

    def make():
        differ = model.differ()

        def step(columns: dict) -> dict:
            x = np.array([features(d) for d in differ([windows_of(t.as_py()) for t in columns["text"]])])
            score = model.score(x.reshape(len(x), len(model.weights)))
            return {f.name: columns[f.name] for f in schema} | {"score": score, "predicted": (score >= 0.5).astype(np.int32)}

        return step

    out = T.StructType([*schema, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    return common.arrow_map(documents.select(*[f.name for f in schema]), make, out, rows=500)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted of all documents.

    Null and empty texts have no windows and get the score of no evidence. Repeated rows are scored alike. Without
    labels of both classes all texts get the share of toxic labels. An empty table gives no rows.
    """
    documents = common.table(spark, sf_dir, "documents", "doc_id", "text")
    model = fitted(documents, common.table(spark, sf_dir, "labels", "doc_id", "toxic"))
    scored = score_documents(documents, model)
    return scored.select("doc_id", (common.fold_bucket(F.col("doc_id")) == 0).alias("held_out"), "score", "predicted")
