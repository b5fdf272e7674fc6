"""SentencePiece encoding and decoding, with a max-plus parallel scan for giant documents.

A text's encoding is a path of pieces from its start to its end. For a unigram model it is the path of
the best summed score. For a BPE model it is the only path all of whose neighbouring pieces are
stable: merging the two pieces' text anew gives the same two pieces. Both are max-plus problems, the second with
scores 0 and minus infinity.

A giant document is cut into chunks of fixed length. The state at a border is the piece that covers the
last character before it. A chunk on its own yields the transfer matrix from the states at its left border to
those at its right one. Matrices combine associatively, which settles the state at every border, and then
each chunk is traced back on its own. Where no piece of the vocabulary has a word boundary inside, paths
are forced through word boundaries; only the words that a border cuts need the matrix, the rest of a chunk is encoded as it is.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nzspan.session import ship, written

from . import common

MARK = "▁"
#: Characters of a chunk; a longer document is cut.
CHUNK = 1 << 15
#: Remembered pairs of pieces of a worker.
MEMORY = 100_000
NONE = float("-inf")


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


@dataclass
class Pieces:
    """A SentencePiece model with what the scan needs to know of it."""

    proto: bytes
    pairs: dict[tuple[str, str], bool] = field(default_factory=dict)

    @cached_property
    def library(self):
        import sentencepiece

        return sentencepiece.SentencePieceProcessor(model_proto=self.proto)

    @cached_property
    def kind(self) -> str:
        """bpe or unigram, from field 3 of the trainer's settings in the model file."""
        for number, value in _fields(self.proto):
            if number == 2:
                for inner, setting in _fields(value):
                    if inner == 3:
                        return {1: "unigram", 2: "bpe"}.get(setting, "other")
                return "unigram"
        return "unigram"

    @cached_property
    def vocabulary(self) -> dict[str, float]:
        sp = self.library
        plain = (i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i)))
        return {sp.id_to_piece(i): sp.get_score(i) for i in plain}

    @cached_property
    def longest(self) -> int:
        return max(map(len, self.vocabulary), default=1)

    @cached_property
    def by_words(self) -> bool:
        """No piece goes over a word boundary, so words encode on their own."""
        return not any(re.search(f"[^{MARK}]{MARK}", p) for p in self.vocabulary)

    @cached_property
    def lowest(self) -> float:
        return min(self.vocabulary.values(), default=0.0) - 10.0  # the library's penalty for an unknown character

    def normalize(self, text: str) -> str:
        return self.library.normalize(text)

    def piece_ids(self, piece: str) -> list[int]:
        """Ids of one piece; an unknown character is told by its bytes where the model has them."""
        sp = self.library
        i = sp.piece_to_id(piece)
        if piece in self.vocabulary:
            return [i]
        told = [sp.piece_to_id(f"<0x{b:02X}>") for b in piece.encode("utf-8", "surrogatepass")]
        return [sp.unk_id()] if sp.unk_id() in told else told

    def inner_ids(self, normal: str) -> list[int]:
        """Ids of normalized text from one word boundary to another."""
        plain = normal[1:].replace(MARK, " ")
        if self.kind == "bpe" and normal[:1] == MARK and self.normalize(plain) == normal:
            return self.library.encode(plain)
        return self.path_ids(normal)

    def stable(self, left: str, right: str) -> bool:
        """Whether the two pieces may stand side by side in an encoding."""
        if self.kind != "bpe":
            return True
        key = (left, right)
        known = self.pairs.get(key)
        if known is None:
            if len(self.pairs) >= MEMORY:
                self.pairs.clear()
            known = self.pairs[key] = self.merged(left + right) == [left, right]
        return known

    def merged(self, text: str) -> list[str]:
        """BPE by its rule: again and again the leftmost pair of the best score becomes one piece."""
        parts = list(text)
        while len(parts) > 1:
            best, at = NONE, -1
            for i in range(len(parts) - 1):
                score = self.vocabulary.get(parts[i] + parts[i + 1], NONE)
                if score > best:
                    best, at = score, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def spans_from(self, text: str, start: int, stop: int) -> list[tuple[int, float]]:
        """(end, score) of the pieces that start here and end by stop."""
        bpe = self.kind == "bpe"
        found = []
        for end in range(start + 1, min(stop, start + self.longest) + 1):
            score = self.vocabulary.get(text[start:end])
            if score is not None:
                found.append((end, 0.0 if bpe else score))
            elif end == start + 1:
                found.append((end, 0.0 if bpe else self.lowest))
        return found

    def lattice(self, text: str, entries: list[tuple[int, int] | None], start: int, goal: int, limit: int) -> dict:
        """Best scores from every entry to every span reached, up to spans that cover the character before goal.

        An entry is a span (s, e) before the path, or None for a path that starts at `start`. Result: node -> (scores
        by entry, previous node by entry); nodes are spans.
        """
        n = len(entries)
        pending: dict[int, dict[tuple[int, int], tuple[np.ndarray, list]]] = {}
        for k, entry in enumerate(entries):
            node = entry if entry is not None else (start, start)
            scores = np.full(n, NONE)
            scores[k] = 0.0
            at = pending.setdefault(node[1], {})
            if node in at:
                at[node][0][k] = 0.0
            else:
                at[node] = (scores, [None] * n)
        done: dict[tuple[int, int], tuple[np.ndarray, list]] = {}
        position = min(pending, default=goal)
        while pending and position < limit + 1:
            arrived = pending.pop(position, None)
            if arrived:
                done |= arrived
                if position < goal:
                    for end, score in self.spans_from(text, position, limit):
                        piece, best, back = text[position:end], None, None
                        for node, (scores, _) in arrived.items():
                            if node[0] < node[1] and not self.stable(text[node[0] : node[1]], piece):
                                continue
                            if best is None:
                                best, back = scores + score, [node] * n
                            else:
                                other = scores + score
                                better = other > best
                                best = np.where(better, other, best)
                                back = [node if b else o for b, o in zip(better, back, strict=True)]
                        if best is not None and np.isfinite(best).any():
                            pending.setdefault(end, {})[(position, end)] = (best, back)
            position = min(pending, default=limit + 1)
        return done

    @staticmethod
    def trace(done: dict, node: tuple[int, int], k: int) -> list[tuple[int, int]]:
        out = []
        while node is not None:
            out.append(node)
            node = done[node][1][k]
        return out[::-1]

    def path_ids(self, text: str) -> list[int]:
        """Encoding of normalized text by the path problem itself."""
        if not text:
            return []
        done = self.lattice(text, [None], 0, len(text), len(text))
        ends = [node for node in done if node[1] == len(text) and node[0] < node[1]]
        last = max(ends, key=lambda node: done[node][0][0])
        return [i for s, e in self.trace(done, last, 0)[1:] for i in self.piece_ids(text[s:e])]

    # --- chunks: text holds the chunk [a, b) with `longest` characters around it where there are any

    def states(self, text: str, border: int) -> list[tuple[int, int]]:
        """Spans of pieces that cover the character before the border."""
        return [(s, e) for s in range(max(0, border - self.longest), border) for e, _ in self.spans_from(text, s, len(text)) if e >= border]

    def forced(self, text: str, a: int, b: int) -> tuple[int, int] | None:
        """First and last place strictly inside [a, b) where any path has an edge."""
        if not self.by_words:
            return None
        places = [m.start() + 1 for m in re.finditer(f"[^{MARK}]{MARK}", text[a:b])]
        return (a + places[0], a + places[-1]) if places else None

    def transfer(self, text: str, a: int, b: int, first: bool, last: bool) -> list[tuple[int, int, int, int, float]]:
        """Non-empty entries (s, e, s', e', score) of a chunk's matrix; (a, a) stands for the text's start, (b, b) for its end."""
        entries = [(a, a)] if first else self.states(text, a)
        exits = [(b, b)] if last else self.states(text, b)
        cut = self.forced(text, a, b)
        if cut is None:
            done = self.lattice(text, [None if first else x for x in entries], a, b, len(text))
            out = []
            for x in exits:
                for k, entry in enumerate(entries):
                    if last:
                        score = max((v[0][k] for node, v in done.items() if node[1] == b), default=NONE)
                    elif x in done and not (x in entries and x != entry):
                        score = done[x][0][k]
                    else:
                        score = NONE
                    if score > NONE:
                        out.append((*entry, *x, float(score)))
            return out
        head = self.lattice(text, [None if first else x for x in entries], a, cut[0], cut[0])
        tail = self.lattice(text, [None], cut[1], b, len(text))
        into = [max((v[0][k] for node, v in head.items() if node[1] == cut[0]), default=NONE) for k in range(len(entries))]
        outof = [max((v[0][0] for node, v in tail.items() if node[1] == b), default=NONE) if last else (tail[x][0][0] if x in tail else NONE) for x in exits]
        return [(*x, *y, float(i + o)) for x, i in zip(entries, into, strict=True) if i > NONE for y, o in zip(exits, outof, strict=True) if o > NONE]

    def backtrace(self, text: str, a: int, b: int, entry: tuple[int, int], leave: tuple[int, int], last: bool) -> list[int]:
        """Ids of the pieces after the entry's, up to and with the exit's."""
        cut = self.forced(text, a, b)
        start = None if entry[0] == entry[1] else entry

        def ids(done: dict, node: tuple[int, int]) -> list[int]:
            return [i for s, e in self.trace(done, node, 0)[1:] for i in self.piece_ids(text[s:e])]

        def best_at(done: dict, place: int) -> tuple[int, int]:
            return max((node for node in done if node[1] == place), key=lambda node: done[node][0][0])

        if cut is None:
            done = self.lattice(text, [start], a, b, len(text))
            return ids(done, best_at(done, b) if last else leave)
        head, tail = self.lattice(text, [start], a, cut[0], cut[0]), self.lattice(text, [None], cut[1], b, len(text))
        return ids(head, best_at(head, cut[0])) + self.inner_ids(text[cut[0] : cut[1]]) + ids(tail, best_at(tail, b) if last else leave)


def _fields(data: bytes):
    """(number, value) of a protocol buffer message: ints, or bytes of length-delimited fields."""
    at = 0

    def number() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(data):
        tag = number()
        wire = tag & 7
        if wire == 0:
            yield tag >> 3, number()
        elif wire == 2:
            size = number()
            yield tag >> 3, data[at : at + size]
            at += size
        else:
            size = 8 if wire == 1 else 4
            yield tag >> 3, data[at : at + size]
            at += size


def combine(entries: list[list[tuple]]) -> list[tuple[tuple[int, int], tuple[int, int]]]:
    """For matrices of consecutive chunks, the (entry, exit) of each on the best path; by pairwise max-plus products.

    Positions are absolute. Products are taken as in a balanced tree; each keeps where it went through, so that the states
    are read off from the root down.
    """
    level = [{(e[:2], e[2:4]): (e[4], None) for e in m} for m in entries]
    tree = [level]
    while len(level) > 1:
        above = []
        for i in range(0, len(level) - 1, 2):
            by_start: dict = {}
            for (u, v), (score, _) in level[i + 1].items():
                by_start.setdefault(u, []).append((v, score))
            product: dict = {}
            for (u, v), (score, _) in level[i].items():
                for w, more in by_start.get(v, ()):
                    if (u, w) not in product or score + more > product[(u, w)][0]:
                        product[(u, w)] = (score + more, v)
            above.append(product)
        if len(level) % 2:
            above.append(level[-1])
        level = above
        tree.append(level)
    chosen = [max(level[0], key=lambda k: level[0][k][0])]
    for depth in range(len(tree) - 1, 0, -1):
        below = []
        for i, (u, w) in enumerate(chosen):
            if 2 * i + 1 < len(tree[depth - 1]):
                via = tree[depth][i][(u, w)][1]
                below += [(u, via), (via, w)]
            else:
                below.append((u, w))
        chosen = below
    return chosen


CHUNKED = "row long, k int, last boolean, origin long, a int, b int, text string"


def _cut(normal: str, chunk: int, longest: int):
    """(k, last, origin, a, b, text) of the chunks: text with what lies around, a and b where the chunk lies in it."""
    n = -(-len(normal) // chunk)
    for k in range(n):
        lo, hi = k * chunk, min(len(normal), (k + 1) * chunk)
        origin = max(0, lo - longest)
        yield k, k == n - 1, origin, lo - origin, hi - origin, normal[origin : hi + longest]


def encode_documents(documents: DataFrame, model: str | None = None, chunk: int = CHUNK) -> DataFrame:
    """(row..., ids array<int>, n_chunks) for every row of documents, text among its columns; all columns stay.

    Null and empty texts have no ids. Columns of the input named ids or n_chunks give way. An empty table gives no rows.
    """
    spark = documents.sparkSession
    ship(spark)
    with open(model or default_model(), "rb") as file:
        proto = file.read()
    keep = [f for f in documents.schema.fields if f.name not in ("ids", "n_chunks")]
    names = [f.name for f in keep]
    giant = F.length(F.coalesce("text", F.lit(""))) > chunk
    schema = T.StructType([*keep, T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("n_chunks", T.IntegerType())])

    def make():
        pieces = Pieces(proto)

        def step(columns: dict) -> dict:
            found = [pieces.library.encode(t.as_py() or "") for t in columns["text"]]
            return {name: columns[name] for name in names} | {"ids": _lists(found), "n_chunks": pa.array([1] * len(found), pa.int32())}

        return step

    plain = common.arrow_map(documents.select(*names).where(~giant), make, schema)

    # giant documents, told apart by their text: equal texts are encoded once
    texts = documents.where(giant).select("text").withColumn("row", F.xxhash64("text")).dropDuplicates(["row", "text"])

    def make_chunks():
        pieces = Pieces(proto)

        def step(columns: dict) -> dict:
            out = {k: [] for k in ("row", "k", "last", "origin", "a", "b", "text")}
            for row, text in zip(columns["row"].to_pylist(), columns["text"], strict=True):
                for piece in _cut(pieces.normalize(text.as_py()), chunk, pieces.longest):
                    for name, value in zip(out, (row, *piece), strict=True):
                        out[name].append(value)
            return out

        return step

    chunks = written(common.arrow_map(texts.select("row", "text"), make_chunks, CHUNKED).repartition("row", "k"), "piece-chunks")

    def make_transfer():
        pieces = Pieces(proto)

        def step(columns: dict) -> dict:
            rows = zip(*(columns[c].to_pylist() for c in ("row", "k", "last", "origin", "a", "b", "text")), strict=True)
            out = {"row": [], "k": [], "matrix": []}
            for row, k, last, origin, a, b, text in rows:
                matrix = [(s + origin, e + origin, t + origin, f + origin, w) for s, e, t, f, w in pieces.transfer(text, a, b, k == 0, last)]
                out["row"].append(row)
                out["k"].append(k)
                out["matrix"].append([dict(zip("setfw", x, strict=True)) for x in matrix])
            return out

        return step

    matrices = common.arrow_map(chunks, make_transfer, "row long, k int, matrix array<struct<s:long,e:long,t:long,f:long,w:double>>")

    def settle(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("k")
        states = combine([[tuple(x[c] for c in "setfw") for x in m] for m in rows["matrix"]])
        flat = [(*u, *v) for u, v in states]
        return pd.DataFrame({"row": rows["row"].to_numpy(), "k": rows["k"].to_numpy()} | {c: [x[i] for x in flat] for i, c in enumerate("setf")})

    settled = matrices.groupBy("row").applyInPandas(settle, "row long, k int, s long, e long, t long, f long")

    def make_trace():
        pieces = Pieces(proto)

        def step(columns: dict) -> dict:
            rows = zip(*(columns[c].to_pylist() for c in ("last", "origin", "a", "b", "text", "s", "e", "t", "f")), strict=True)
            found = [pieces.backtrace(text, a, b, (s - o, e - o), (t - o, f - o), last) for last, o, a, b, text, s, e, t, f in rows]
            return {"row": columns["row"], "k": columns["k"], "part": _lists(found)}

        return step

    traced = common.arrow_map(chunks.join(settled, ["row", "k"]), make_trace, "row long, k int, part array<int>")
    whole = traced.groupBy("row").agg(F.sort_array(F.collect_list(F.struct("k", "part"))).alias("parts"))
    whole = whole.select("row", F.flatten(F.col("parts.part")).alias("ids"), F.size("parts").alias("n_chunks"))
    large = documents.select(*names).where(giant).withColumn("row", F.xxhash64("text")).join(whole, "row").select(*names, "ids", "n_chunks")
    return plain.unionByName(large)


def _lists(values: list[list[int]]) -> pa.Array:
    offsets = np.zeros(len(values) + 1, np.int32)
    np.cumsum([len(v) for v in values], out=offsets[1:])
    flat = np.fromiter((i for v in values for i in v), np.int32, int(offsets[-1]))
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))


def decode_documents(encoded: DataFrame, model: str | None = None) -> DataFrame:
    """(row..., decoded) for every row with an ids array; null ids decode to an empty text."""
    ship(encoded.sparkSession)
    with open(model or default_model(), "rb") as file:
        proto = file.read()
    keep = [f for f in encoded.schema.fields if f.name != "decoded"]

    def make():
        pieces = Pieces(proto)

        def step(columns: dict) -> dict:
            return {f.name: columns[f.name] for f in keep} | {"decoded": [pieces.library.decode(ids.as_py() or []) for ids in columns["ids"]]}

        return step

    return common.arrow_map(encoded.select(*[f.name for f in keep]), make, T.StructType([*keep, T.StructField("decoded", T.StringType())]))


def with_digest(encoded: DataFrame, model: str | None = None) -> DataFrame:
    """(row..., n_ids, ids_crc32, restored) for rows with text and ids, in one pass.

    ids_crc32 is the crc32 of the ids as little-endian unsigned 32-bit integers; restored: decoding gives the text again.
    """
    ship(encoded.sparkSession)
    with open(model or default_model(), "rb") as file:
        proto = file.read()
    new = [T.StructField("n_ids", T.LongType()), T.StructField("ids_crc32", T.LongType()), T.StructField("restored", T.BooleanType())]
    keep = [f for f in encoded.schema.fields if f.name not in {f.name for f in new}]

    def make():
        pieces = Pieces(proto)

        def step(columns: dict) -> dict:
            out = {"n_ids": [], "ids_crc32": [], "restored": []}
            for ids, text in zip(columns["ids"], columns["text"], strict=True):
                array = ids.values.to_numpy() if ids.is_valid else np.zeros(0, np.int32)
                out["n_ids"].append(len(array))
                out["ids_crc32"].append(zlib.crc32(array.astype("<u4").tobytes()))
                out["restored"].append(pieces.library.decode(array.tolist()) == (text.as_py() or ""))
            return {f.name: columns[f.name] for f in keep} | out

        return step

    return common.arrow_map(encoded.select(*[f.name for f in keep]), make, T.StructType([*keep, *new]))


def op4_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_ids, ids_crc32, n_chunks, and whether decoding gives the text again, for all documents.

    Null and empty texts have no ids. Repeated rows are encoded each. An empty table gives no rows. Other columns are left aside.
    """
    encoded = encode_documents(common.table(spark, sf_dir, "documents", "doc_id", "text"))
    return with_digest(encoded).select("doc_id", "n_ids", "ids_crc32", "n_chunks", "restored")
