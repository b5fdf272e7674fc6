"""A hidden Markov language model over words, trained on the cluster.

Tokens are words in lower case and one end token for each text. Every word's count in the training texts is taken. The most
frequent words are classes of their own; all others, unknown ones too, fall into classes by their last two bytes. A state emits a
class, and a class its words by their counts plus one half, with one half for an unknown word. Baum-Welch takes whole passes over the
training texts, until one gains too little (TOLERANCE): each task adds up expected counts, which one aggregate sums. The scaled
forward recursion gives a text's exact likelihood.

Texts advance in step, many at a time, those that are longer outlasting the shorter. What concerns the count of
a rare word comes by a join on the word, so no table that grows with the vocabulary leaves the cluster.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from nzspan.session import ship, written

from . import common

#: The end token; no word has white space.
END = b"\n"
STATES, OWN, SUFFIXES = 12, 8192, 256
#: Words whose counts every task has; tokens of texts that advance together.
KNOWN, TOGETHER = 65536, 300_000
#: Training stops when a pass lifts the logarithm of the likelihood by less than this share of it.
TOLERANCE, PRIOR = 1e-3, 20.0
#: Steps of a recursion from one scaling to the next, in double and in single precision; a sum that counts as none in the latter.
RESCALE, RESCALE_SINGLE, LEAST = 16, 4, 1e-37


def suffix_class(word: bytes) -> int:
    return zlib.crc32(word[-2:]) % SUFFIXES


class Index(dict):
    """Places of words, -1 for all others."""

    def __missing__(self, word: bytes) -> int:
        return -1


@dataclass
class Vocabulary:
    """The most frequent words with their counts, and totals. The first OWN are classes."""

    words: list[bytes]
    counts: np.ndarray
    total: int  # tokens in training texts
    distinct: int
    mass: np.ndarray  # of each suffix class: counts plus one half of its words, and one half

    def __post_init__(self):
        self.index = Index((w, i) for i, w in enumerate(self.words))
        own = min(OWN, len(self.words))
        self.classes = np.array([i if i < own else OWN + suffix_class(w) for i, w in enumerate(self.words)], np.int64)
        self.log_count = np.log10(self.counts + 0.5)
        self.log_mass = np.log10(self.mass)
        self.log_base = math.log10(self.total + 0.5 * (self.distinct + 1))

    def read(self, text: str | None) -> tuple[np.ndarray, Counter, float, float]:
        """Classes of a text's tokens, its words of unknown count, and the known words' summed log10 counts and in-class log10 shares."""
        words = common.byte_words(text)
        words.append(END)
        at = np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))
        missing = np.flatnonzero(at < 0)
        others = [words[i] for i in missing.tolist()]
        rare = Counter(others)
        classes = np.where(at >= 0, self.classes[at], 0) if len(self.classes) else np.zeros(len(at), np.int64)
        classes[missing] = [OWN + zlib.crc32(w[-2:]) % SUFFIXES for w in others]
        known = at[at >= 0]
        in_class = self.log_count[known[known >= OWN]].sum() - self.log_mass[classes[classes >= OWN] - OWN].sum()
        return classes, rare, float(self.log_count[known].sum()), float(in_class)


@dataclass
class Chain:
    start: np.ndarray
    move: np.ndarray
    emit: np.ndarray  # class by state

    @classmethod
    def random(cls, share: np.ndarray, states: int = STATES, seed: int = 42) -> Chain:
        rng = np.random.default_rng(seed)
        emit = share[:, None] * rng.gamma(4.0, size=(len(share), states))
        move = np.full((states, states), 0.3 / states) + 0.7 * np.eye(states)
        return cls(np.full(states, 1.0 / states), move, emit / emit.sum(axis=0))

    @classmethod
    def from_counts(cls, start: np.ndarray, move: np.ndarray, emit: np.ndarray, share: np.ndarray) -> Chain:
        start, move, emit = start + 0.1, move + 0.1, emit + PRIOR * share[:, None]
        return cls(start / start.sum(), move / move.sum(axis=1, keepdims=True), emit / emit.sum(axis=0))

    def forward(self, flat: np.ndarray, alive: list[int], seen: np.ndarray, out: np.ndarray | None, rescale: int) -> tuple[np.ndarray, np.ndarray]:
        """(what each text was scaled by, step by step; sums of the last states): the forward recursion, in out if it is given.

        Only every so many steps are scaled, which the numbers of seen must have room for.
        """
        move = self.move.astype(seen.dtype)
        ones = np.ones(len(self.start), seen.dtype)  # a product with it adds up rows several times as fast as sum does
        ends = np.cumsum(alive).tolist()
        scales = np.ones(len(flat))
        last = np.empty(alive[0])
        two = np.empty((2, alive[0], len(self.start))) if out is None else None
        before, tiny = None, np.finfo(seen.dtype).tiny
        for t, n in enumerate(alive):
            hi = ends[t]
            lo = hi - n
            state = out[lo:hi] if out is not None else two[t & 1, :n]
            if t:
                m = len(before)
                if m > n:
                    last[n:m] = before[n:].dot(ones)
                np.dot(before[:n], move, out=state)
            else:
                state[:] = self.start
            state *= seen[lo:hi]
            if t % rescale == rescale - 1:
                scale = 1.0 / np.maximum(state.dot(ones), tiny)
                state *= scale[:, None]
                scales[lo:hi] = scale
            before = state
        last[: len(before)] = before.dot(ones)
        return scales, last

    def likelihood(self, texts: list[np.ndarray]) -> np.ndarray:
        """log10 probability of every sequence of classes."""
        out = np.zeros(len(texts))
        for order, flat, alive in together(texts):
            scales, last = self.forward(flat, alive, self.emit.take(flat, axis=0), None, RESCALE)
            logs, ends = np.log10(last), np.cumsum(alive).tolist()
            for t in range(RESCALE - 1, len(alive), RESCALE):
                logs[: alive[t]] -= np.log10(scales[ends[t] - alive[t] : ends[t]])
            out[order] = logs
        return out

    def expect(self, texts: list[np.ndarray], start: np.ndarray, move: np.ndarray, emit: np.ndarray) -> float:
        """Add the expected counts of a forward and backward recursion to start, move and emit; the log10 probability of all texts."""
        states, told = len(self.start), 0.0
        # single precision, for which each class's chances are taken by the largest of them
        turned, ones = np.ascontiguousarray(self.move.T.astype(np.float32)), np.ones(states, np.float32)
        peak = np.maximum(self.emit.max(axis=1), 1e-300)
        emits = (self.emit / peak[:, None]).astype(np.float32)
        for _, flat, alive in together(texts):
            ends = np.cumsum(alive).tolist()
            seen = emits.take(flat, axis=0)
            ahead = np.empty((len(flat), states), np.float32)  # forward, then the states' probabilities
            scales, last = self.forward(flat, alive, seen, ahead, RESCALE_SINGLE)
            told += float(np.log10(np.maximum(last, LEAST)).sum() - np.log10(scales).sum() + np.bincount(flat, minlength=len(peak)) @ np.log10(peak))
            back = np.ones((len(flat), states), np.float32)
            for t in range(len(alive) - 2, -1, -1):
                lo, hi, m = ends[t] - alive[t], ends[t], alive[t + 1]
                follows, here = seen[hi : hi + m], back[lo : lo + m]
                follows *= back[hi : hi + m]  # now with all that follows
                np.dot(follows, turned, out=here)
                if t % RESCALE_SINGLE == 0:
                    here *= (1.0 / np.maximum(here.dot(ones), LEAST))[:, None]
            both = np.maximum(np.einsum("ij,ij->i", ahead, back), LEAST)
            first = alive[0]
            if len(flat) > first:
                # where the token before each one stands
                before = np.arange(first, len(flat)) - np.repeat(alive[:-1], alive[1:])
                seen[first:] *= (scales[first:] / both[first:]).astype(np.float32)[:, None]
                move += self.move * (ahead.take(before, axis=0).T @ seen[first:])
            ahead *= back
            ahead /= both[:, None]
            start += ahead[:first].sum(axis=0, dtype=np.float64)
            for k in range(states):
                emit[:, k] += np.bincount(flat, weights=ahead[:, k], minlength=len(emit))
        return told


def together(texts: list[np.ndarray]):
    """(places, tokens step by step, texts alive at each step) of groups of texts, the longest first."""
    sizes = np.array([len(t) for t in texts])
    order = np.argsort(-sizes, kind="stable")
    cuts = np.flatnonzero(np.diff(np.cumsum(sizes[order]) // TOGETHER)) + 1
    for group in np.split(order, cuts):
        if not len(group):
            continue
        lengths = sizes[group]
        alive = np.bincount(lengths, minlength=lengths[0] + 1)[::-1].cumsum()[::-1][1:]
        first = np.concatenate([[0], np.cumsum(alive)[:-1]])
        flat = np.empty(int(lengths.sum()), np.int64)
        for lane, i in enumerate(group):
            flat[first[: lengths[lane]] + lane] = texts[i]
        yield group, flat, alive.tolist()


def count_words(documents: DataFrame) -> DataFrame:
    """(word binary, c long) over all tokens of documents(text), the end token too."""
    ship(documents.sparkSession)

    def make():
        def step(columns: dict) -> dict:
            found: Counter = Counter()
            for t in columns["text"]:
                found.update(common.byte_words(t.as_py()))
            found[END] += len(columns["text"])
            return {"word": pa.array(list(found), pa.binary()), "c": list(found.values())}

        return step

    return common.arrow_map(documents.select("text"), make, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))


def vocabulary(counts: DataFrame) -> Vocabulary:
    """Totals and up to KNOWN of the most frequent words of counts(word, c)."""
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    # words of the largest counts, as many whole classes of equal counts as KNOWN has room for
    classes = counts.groupBy("c").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("c").desc()).limit(KNOWN).toPandas()
    fits = classes["c"][classes["n"].cumsum() <= KNOWN]
    least = int(fits.min()) if len(fits) else int(classes["c"].max() or 0) + 1 if len(classes) else 1
    top = counts.where(F.col("c") >= least).toPandas().sort_values(["c", "word"], ascending=[False, True])
    words, number = [bytes(w) for w in top["word"]], top["c"].to_numpy(np.int64)
    if END not in words[:OWN]:  # the end is a class of its own
        own = [r["c"] for r in counts.where(F.col("word") == F.lit(END)).collect()]
        rest = [i for i, w in enumerate(words) if w != END]
        words, number = [END] * len(own) + [words[i] for i in rest], np.concatenate([np.array(own, np.int64), number[rest]])
    mass = np.full(SUFFIXES, 0.5)
    own = set(words[:OWN])

    def make():
        def step(columns: dict) -> dict:
            got = np.zeros(SUFFIXES)
            for w, c in zip(columns["word"].to_pylist(), columns["c"].to_pylist(), strict=True):
                if w not in own:
                    got[suffix_class(w)] += c + 0.5
            return {"k": np.arange(SUFFIXES, dtype=np.int32), "m": got}

        return step

    for k, m in common.arrow_map(counts, make, "k int, m double").groupBy("k").agg(F.sum("m")).collect():
        mass[k] += m
    return Vocabulary(words, number, int(total), int(distinct), mass)


def class_shares(v: Vocabulary) -> np.ndarray:
    share = np.full(OWN + SUFFIXES, 1e-9)
    own = min(OWN, len(v.words))
    share[:own] += v.counts[:own] + 0.5
    share[OWN:] += v.mass
    return share / share.sum()


READ = "row long, doc_id long, held_out boolean, n_tokens long, known long, known_log double, in_class double, classes array<int>, rare array<struct<word:binary,times:long>>"


def read_documents(documents: DataFrame, v: Vocabulary) -> DataFrame:
    """A row of READ for every row of documents(doc_id, text, held_out): tokens as classes, and what their words add to either score."""

    def run(batches):
        from pyspark import TaskContext

        row = TaskContext.get().partitionId() << 33
        for batch in (whole.slice(lo, common.ROWS) for whole in batches for lo in range(0, whole.num_rows, common.ROWS)):
            read = [v.read(t.as_py()) for t in batch.column(1)]
            rare = [r[1] for r in read]
            items = pa.StructArray.from_arrays([pa.array([w for r in rare for w in r], pa.binary()), pa.array([n for r in rare for n in r.values()], pa.int64())], names=["word", "times"])
            sizes = np.array([len(r[0]) for r in read], np.int64)
            offsets = lambda n: pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.arange(row, row + len(read))),
                    batch.column(0),
                    batch.column(2),
                    pa.array(sizes),
                    pa.array(sizes - np.array([sum(r.values()) for r in rare], np.int64)),
                    pa.array([r[2] for r in read], pa.float64()),
                    pa.array([r[3] for r in read], pa.float64()),
                    pa.ListArray.from_arrays(offsets(sizes), pa.array(np.concatenate([np.empty(0, np.int32), *[r[0].astype(np.int32) for r in read]]))),
                    pa.ListArray.from_arrays(offsets([len(r) for r in rare]), items),
                ],
                names=["row", "doc_id", "held_out", "n_tokens", "known", "known_log", "in_class", "classes", "rare"],
            )
            row += len(read)

    return documents.select("doc_id", "text", "held_out").mapInArrow(common.frugal(run), READ)


def train(documents: DataFrame, v: Vocabulary, states: int = STATES, passes: int | None = None, seed: int = 42) -> Chain:
    """A chain from documents(text) by passes over all texts: so many, or until one gains less than TOLERANCE."""
    told = documents.select(F.lit(None).cast("long").alias("doc_id"), "text", F.lit(False).alias("held_out"))
    return train_classes(written(read_documents(told, v).select("classes"), "markov-classes"), v, states, passes, seed)


def train_classes(encoded: DataFrame, v: Vocabulary, states: int = STATES, passes: int | None = None, seed: int = 42) -> Chain:
    """As train, from texts that were read: encoded(classes)."""
    share = class_shares(v)
    size = len(share)
    chain = Chain.random(share, states, seed)
    names = [f"s{k}" for k in range(states)]
    before, done = -math.inf, 0
    while passes is None or done < passes:

        def run(batches, chain=chain):
            sums = np.zeros(states), np.zeros((states, states)), np.zeros((size, states))
            told = np.zeros((1, states))
            for batch in batches:
                column = batch.column(0)
                values, cuts = column.values.to_numpy(), column.offsets.to_numpy()
                told[0, 0] += chain.expect([values[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)], *sums)
            rows = np.vstack([sums[0][None, :], *sums[1:], told])
            some = np.flatnonzero(rows.any(axis=1))
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), *[pa.array(rows[some, k]) for k in range(states)]], names=["i", *names])

        found = encoded.mapInArrow(common.frugal(run), "i int, " + ", ".join(f"{n} double" for n in names))
        # a row for each state and class at most, and one for the likelihood
        total = found.groupBy("i").agg(*[F.sum(n).alias(n) for n in names]).toPandas().sort_values("i")
        rows = np.zeros((2 + states + size, states))
        rows[total["i"].to_numpy()] = total[names].to_numpy()
        chain = Chain.from_counts(rows[0], rows[1 : 1 + states], rows[1 + states : -1], share)
        now, done = float(rows[-1, 0]), done + 1
        if passes is None and now - before <= TOLERANCE * abs(now):
            break
        before = now
    return chain


def score_documents(documents: DataFrame, held_out: Column, states: int = STATES, passes: int | None = None, seed: int = 42) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row of documents(doc_id, text).

    Rows where held_out is true are scored only. Null and empty texts are one end token. Without training texts every class
    is equally likely. Repeated rows count and are scored each. An empty table gives no rows.
    """
    spark = documents.sparkSession
    ship(spark)
    documents = documents.select("doc_id", "text", held_out.alias("held_out"))
    training = documents.where(~F.coalesce("held_out", F.lit(False)))
    counts = written(count_words(training), "markov-counts")
    v = vocabulary(counts)
    # words are looked up once, not in every pass
    read = written(read_documents(documents, v), "markov-read")
    chain = train_classes(read.where(~F.coalesce("held_out", F.lit(False))).select("classes"), v, states, passes, seed)
    kept = ["row", "doc_id", "held_out", "n_tokens", "known", "known_log"]

    def make():
        def step(columns: dict) -> dict:
            values, cuts = columns["classes"].values.to_numpy(), columns["classes"].offsets.to_numpy()
            like = chain.likelihood([values[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)])
            return {c: columns[c] for c in kept} | {"score": like + columns["in_class"].to_numpy()}

        return step

    scored = common.arrow_map(read.select(*kept, "in_class", "classes"), make, "row long, doc_id long, held_out boolean, n_tokens long, known long, known_log double, score double", rows=1 << 20)
    rare = read.select("row", F.explode("rare").alias("r")).select("row", "r.word", "r.times")
    met = rare.join(counts, "word", "left")
    log = F.col("times") * F.log10(F.coalesce("c", F.lit(0)) + 0.5)
    met = met.groupBy("row").agg(F.sum(log).alias("rare_log"), F.sum(F.when(F.col("c") > 0, F.col("times")).otherwise(0)).alias("rare_known"))
    joined = scored.join(met, "row", "left")
    rare_log = F.coalesce("rare_log", F.lit(0.0))
    return joined.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("known") + F.coalesce("rare_known", F.lit(0))).alias("n_known"),
        F.lit(v.total).cast("long").alias("train_tokens"),
        (F.col("known_log") + rare_log - F.col("n_tokens") * F.lit(v.log_base)).alias("base_score"),
        (F.col("score") + rare_log).alias("score"),
    )


def op9_hidden_markov(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of all documents.

    Null and empty texts are one end token. Rows without a doc_id are trained on. Repeated rows count and are scored each. Without
    training texts every class is equally likely. An empty table gives no rows. Other columns are left aside.
    """
    documents = common.table(spark, sf_dir, "documents", "doc_id", "text")
    return score_documents(documents, F.coalesce(common.fold_bucket(F.col("doc_id")) == 1, F.lit(False)))
