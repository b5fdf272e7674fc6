"""Token ids of documents in files: blocks of the range coder, in ascending order of documents.

The files are Parquet tables of blocks, written and read by Spark, so that any store will do and a lost task leaves
nothing half written. A shard is a range of documents. Columns: shard, block (ascending within the shard), doc_ids and sizes of
the block's documents, ids_before (ids of the shard before the block), payload (see coder).
"""

from __future__ import annotations

import os
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nzspan.session import shared_folder, ship

from . import coder, common

#: Ids of a block: lanes enough for vector arithmetic.
BLOCK = 2_000_000
#: Remembered words of a worker; new words that the library gets as one text.
MEMORY, TOGETHER = 2_000_000, 256
#: Characters of text encoded at once.
BATCH = 16_000_000
END = 0
SCHEMA = "shard int, block long, doc_ids array<long>, sizes array<int>, ids_before long, payload binary"
_BORDER = re.compile(r"(?<=\S)(?= \S)")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _found(keys: pa.Array, among: pa.Array) -> np.ndarray:
    """Where keys stand among others, -1: nowhere."""
    return pc.index_in(keys, value_set=among).fill_null(-1).to_numpy().astype(np.int64)


class Encoder:
    """Encoding with the tokenizers library, a word at a time, words being remembered.

    The byte-level pattern always breaks before a single space between two other characters, so what stands between such breaks
    encodes on its own. Words are cut, told apart and looked up as Arrow columns, a whole batch at a time. Keys are words without the
    space before them; what has none before it is kept with one, which no other key begins with. New words go to the library many
    together, and are told apart by the space that their first token begins with.
    """

    def __init__(self, settings: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_str(settings)
        vocabulary = self.library.get_vocab(with_added_tokens=True)
        self.spaced = np.zeros(max(vocabulary.values(), default=0) + 1, bool)
        self.spaced[[i for token, i in vocabulary.items() if token.startswith("\u0120")]] = True  # a space in byte-level tokens
        self.forget()

    def forget(self) -> None:
        self.keys = pa.array([], pa.large_string())
        self.ids, self.ends = np.zeros(0, np.uint32), np.zeros(1, np.int64)  # key k has the ids from ends[k] to ends[k + 1]

    @staticmethod
    def clean(word: str) -> bool:
        """Whether spaces on both sides of this word are breaks of the pattern."""
        return bool(word) and not word[0].isspace() and not word[-1].isspace()

    def encode_batch(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.keys) > MEMORY:
            self.forget()
        parts = [t.partition(" ") for t in texts]
        cut = pc.split_pattern(pa.array([p[2] if p[1] else None for p in parts], pa.large_string()), " ")
        sizes = pc.list_value_length(cut).fill_null(0).to_numpy().astype(np.int64)
        words = cut.flatten()
        keys = pa.concat_arrays([words, pa.array([" " + p[0] for p in parts], pa.large_string())])
        where = _found(keys, self.keys)
        odd = {i for i, p in enumerate(parts) if not self.clean(p[0])}
        odd.update(np.repeat(np.arange(len(texts)), sizes).take(self.add(keys, where)).tolist())
        # texts with a break that is none of the pattern's are cut by it
        pieces = {i: [w[1:] if k and self.clean(w[1:]) else " " + w for k, w in enumerate(_BORDER.split(texts[i]))] for i in sorted(odd)}
        if odd:
            others = pa.array([w for p in pieces.values() for w in p], pa.large_string())
            of_pieces = _found(others, self.keys)
            self.add(others, of_pieces)
        starts = np.cumsum(sizes + 1) - sizes - 1
        order = np.zeros(len(keys), np.int64)
        rest = np.ones(len(order), bool)
        rest[starts] = False
        order[starts], order[rest] = where[len(words) :], where[: len(words)]
        found = self._written(order, starts)
        if odd:
            lengths = np.array([len(p) for p in pieces.values()])
            for i, ids in zip(pieces, self._written(of_pieces, np.cumsum(lengths) - lengths), strict=True):
                found[i] = ids
        return found

    def _written(self, places: np.ndarray, starts: np.ndarray) -> list[np.ndarray]:
        """The ids of the keys at these places one after another, cut where those of the keys at starts begin."""
        if not len(places):
            return []
        kept = pa.Array.from_buffers(pa.large_binary(), len(self.keys), [None, pa.py_buffer(4 * self.ends), pa.py_buffer(self.ids)])
        taken = kept.take(pa.array(places))
        _valid, ends, ids = taken.buffers()
        begin = np.frombuffer(ends, np.int64, len(taken) + 1)[starts] // 4
        return np.split(np.frombuffer(ids, np.uint32) if ids and ids.size else np.zeros(0, np.uint32), begin)[1:]

    def add(self, keys: pa.Array, where: np.ndarray) -> np.ndarray:
        """Encode and remember the keys that are nowhere yet, and tell where they are now; returns the positions of words that are not clean, which stay out."""
        at = np.flatnonzero(where < 0)
        if not len(at):
            return at
        unseen = keys.take(pa.array(at)).dictionary_encode()
        names, which = unseen.dictionary.to_pylist(), unseen.indices.to_numpy()
        fit = np.array([" " in w or self.clean(w) for w in names], bool)
        before = len(self.keys)
        self.remember([w for w, f in zip(names, fit.tolist(), strict=True) if f])
        place = before + _found(unseen.dictionary, self.keys.slice(before))
        where[at] = np.where(fit, place, 0).take(which)
        return at[~fit.take(which)]

    def remember(self, keys: list[str]) -> None:
        alone = [w for w in keys if " " in w]
        together = [w for w in keys if " " not in w]
        some = [together[lo : lo + TOGETHER] for lo in range(0, len(together), TOGETHER)]
        names, ids, lengths = [], [], []
        for words, found in zip(some, self.library.encode_batch_fast([" " + " ".join(w) for w in some], add_special_tokens=False), strict=True):
            one = np.array(found.ids, np.uint32)
            starts = np.flatnonzero(self.spaced[one])
            if len(starts) != len(words):  # not told apart by spaces
                alone += words
                continue
            names += words
            ids.append(one)
            lengths.append(np.diff(starts, append=len(one)))
        for found in self.library.encode_batch_fast([w[1:] if w[:1] == " " else " " + w for w in alone], add_special_tokens=False):
            ids.append(np.array(found.ids, np.uint32))
            lengths.append([len(ids[-1])])
        if not ids:
            return
        self.keys = pa.concat_arrays([self.keys, pa.array(names + alone, pa.large_string())])
        self.ids = np.concatenate([self.ids, *ids])
        self.ends = np.concatenate([self.ends, self.ends[-1] + np.cumsum(np.concatenate(lengths))])


_encoders: dict[str, Encoder] = {}


def encoder_of(settings: str) -> Encoder:
    """The worker's encoder, whose words stay from task to task."""
    if settings not in _encoders:
        _encoders.clear()
        _encoders[settings] = Encoder(settings)
    return _encoders[settings]


def _slices(texts: list[str]):
    """(from, to): texts together up to BATCH characters, longer ones alone."""
    lo = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > BATCH:
            yield lo, i
            lo, size = i, 0
        size += len(t)
    if lo < len(texts):
        yield lo, len(texts)


def write_token_files(documents: DataFrame, path: str, tokenizer: str | None = None, end: int = END, block: int = BLOCK) -> None:
    """Write the ids of documents(doc_id, text), each with the end id after it, to path; null texts count as empty, null doc_ids come first."""
    spark = documents.sparkSession
    ship(spark)
    with open(tokenizer or default_tokenizer(), encoding="utf-8") as file:
        settings = file.read()
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    ordered = documents.select("doc_id", "text").repartitionByRange(parts, "doc_id").sortWithinPartitions("doc_id", "text")

    def run(batches):
        from pyspark import TaskContext

        encoder, shard = encoder_of(settings), TaskContext.get().partitionId()
        number = before = 0
        docs, held, size = [], [], 0

        def record():
            ids = np.concatenate(held)
            values = (shard, number, docs, [len(h) for h in held], before, coder.encode_block(ids))
            kinds = (pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.int64(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], names=["shard", "block", "doc_ids", "sizes", "ids_before", "payload"])

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), [t or "" for t in batch.column(1).to_pylist()]
            for lo, hi in _slices(texts):
                for doc, found in zip(ids[lo:hi], encoder.encode_batch(texts[lo:hi]), strict=True):
                    docs.append(doc)
                    held.append(np.append(found, np.uint32(end)))
                    size += len(held[-1])
                    if size >= block:
                        yield record()
                        number, before = number + 1, before + size
                        docs, held, size = [], [], 0
        if docs:
            yield record()

    ordered.mapInArrow(common.frugal(run), SCHEMA).write.parquet(path)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, ids array<long>) of every document in the files; start counts the ids of all documents before it.

    A damaged block raises coder.Damaged.
    """
    return _read(spark, path, "ids array<long>", lambda ids: {"ids": ids.astype(np.int64)})


def _read(spark: SparkSession, path: str, more: str, tell) -> DataFrame:
    ship(spark)
    blocks = spark.read.schema(SCHEMA).parquet(path)
    per_shard = blocks.groupBy("shard").agg(F.sum(F.aggregate("sizes", F.lit(0).cast("long"), lambda a, x: a + x)).alias("total"))
    shards = per_shard.select("shard", F.coalesce(F.sum("total").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))

    def make():
        def step(columns: dict) -> dict:
            out: dict[str, list] = {}
            for shard, docs, sizes, before, payload in zip(*(columns[c] for c in ("shard", "doc_ids", "sizes", "ids_before", "payload")), strict=True):
                ids, at, start = coder.decode_block(payload.as_py()), 0, before.as_py()
                for doc, size in zip(docs.as_py(), sizes.as_py(), strict=True):
                    row = {"shard": shard.as_py(), "doc_id": doc, "local": start + at, "n_tokens": size} | tell(ids[at : at + size])
                    for k, v in row.items():
                        out.setdefault(k, []).append(v)
                    at += size
            return out or None

        return step

    found = common.arrow_map(blocks, make, f"shard int, doc_id long, local long, n_tokens long, {more}")
    # one row for each shard, of which there are as many as tasks wrote
    return found.join(F.broadcast(shards), "shard").withColumn("start", F.col("offset") + F.col("local")).drop("shard", "offset", "local")


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of all documents, from the files that hold their ids.

    Null texts count as empty and have the end id only; repeated rows are written as often; no rows make no block and no result.
    """
    import uuid

    path = f"{shared_folder(spark)}/token-files-{uuid.uuid4().hex}"
    write_token_files(common.table(spark, sf_dir, "documents", "doc_id", "text"), path)
    found = _read(spark, path, "ids_crc32 long", lambda ids: {"ids_crc32": zlib.crc32(ids.astype("<u4").tobytes())})
    return found.select("doc_id", "start", "n_tokens", "ids_crc32")
