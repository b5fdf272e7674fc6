"""Removal of repeated byte strings with a sparse suffix array.

A byte goes if a string of `length` bytes that covers it also starts elsewhere, in any document or the same
one. Sorting a suffix for every byte would move hundreds of times the corpus. It is enough to sort the suffixes
that start at anchors, places chosen by content alone:

1. Every window of `length` bytes has an anchor, the start of its `gram`-byte string with the least hash. Equal
   windows have equal anchors at equal offsets. About one byte in 170 is an anchor.
2. Anchors whose gram occurs once cannot lie in a repeated window; only the others go on, with the bytes that
   windows around them may hold: up to length - gram to the left, up to length to the right.
3. Suffixes from anchors are range-partitioned by their leading bytes, with splitters from a sample. Each bucket sorts
   its suffixes, and the reversed texts to their left, by multikey quicksort on words of eight bytes. The common prefixes
   of neighbours give, for every offset d, the classes of suffixes that agree on d bytes to the left and length - d to
   the right: a window is repeated iff its class has two members.
4. A gram with more suffixes than a bucket should hold is spread over sub-buckets. What is single within its sub-bucket
   is compared across their boundaries by one aggregate, to which each sub-bucket adds a class once.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nzspan.session import discard, ship, written

from . import common

LENGTH, GRAM = 400, 64
#: Suffixes of one gram that one bucket takes; bytes of text worked on at once; suffixes sorted, and offsets compared, at once.
CROWD, PIECE, ROWS, COLUMNS = 32768, 1 << 18, 1024, 32
#: Contexts that a task remembers.
MEMORY = 200_000
#: Sampled suffixes for the splitters.
SAMPLE = 100_000
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


def _byte_values() -> np.ndarray:
    x = (np.arange(256, dtype=np.uint64) + np.uint64(1)) * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(29))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(32))
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    return x


class Hasher:
    """Hashes of all windows of a width in a piece of bytes, from one running sum."""

    def __init__(self, longest: int):
        self.up = _powers(_BASE, longest + 1)
        self.down = _powers(pow(_BASE, -1, 1 << 64), longest + 1)
        self.values = _byte_values()

    def windows(self, data: np.ndarray, width: int) -> np.ndarray:
        total = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.values[data] * self.up[: len(data)], out=total[1:])
        return _mixed((total[width:] - total[:-width]) * self.down[: len(data) - width + 1])


def _slide(x: np.ndarray, width: int, pick) -> np.ndarray:
    """pick over every window of that width."""
    done = 1
    out = x
    while done * 2 <= width:
        out = pick(out[:-done], out[done:])
        done *= 2
    return out if done == width else pick(out[: len(out) - (width - done)], out[width - done :])


def anchors(data: np.ndarray, ends: np.ndarray, hasher: Hasher, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Positions and gram hashes of the anchors of texts that lie end to end in data; ends: where each text ends."""
    if len(data) < length:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    hashes = hasher.windows(data, gram) | np.uint64(1)
    span = length - gram + 1
    least = _slide(hashes, span, np.minimum)  # of the window that starts here
    room = np.repeat(ends, np.diff(ends, prepend=0))[: len(least)] - np.arange(len(least))
    least[room < length] = 0
    around = np.zeros(len(least) + 2 * (span - 1), np.uint64)
    around[span - 1 : span - 1 + len(least)] = least
    at = np.flatnonzero(_slide(around, span, np.maximum) == hashes)
    return at, hashes[at]


def _pieces(offsets: np.ndarray, length: int):
    """(from, to, text ends): texts together up to PIECE bytes, longer ones in overlapping pieces."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + PIECE, "right")) - 1)
        a, b = int(offsets[lo]), int(offsets[hi])
        if b - a <= PIECE:
            yield a, b, offsets[lo + 1 : hi + 1] - a
        else:  # one long text
            for start in range(a, max(b - length + 1, a + 1), PIECE - length + 1):
                stop = min(b, start + PIECE)
                yield start, stop, np.array([stop - start])
        lo = hi


def _flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column end to end, and where each text starts, with the last end."""
    column = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] and column.buffers()[2].size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def find_anchors(keyed: DataFrame, length: int, gram: int) -> DataFrame:
    """(doc, mark, pos, gram, lead, new) of keyed(doc, mark, text); lead: the first eight bytes of the gram as a number that sorts alike; new: 1 at a text's first such gram, else 0."""

    def make():
        hasher = Hasher(PIECE)

        def step(columns: dict) -> dict | None:
            data, offsets = _flat(columns["text"])
            places, grams = [], []
            for a, b, ends in _pieces(offsets, length):
                at, g = anchors(data[a:b], ends, hasher, length, gram)
                places.append(at + a)
                grams.append(g)
            if not places:
                return None
            at, first = np.unique(np.concatenate(places), return_index=True)
            g = np.concatenate(grams)[first]
            row = np.searchsorted(offsets, at, "right") - 1
            lead = np.zeros(len(at), np.uint64)
            for k in range(8):
                lead = (lead << np.uint64(8)) | data[at + k].astype(np.uint64)
            lead ^= np.uint64(1 << 63)
            take = pa.array(row)
            order = np.lexsort((at, g, row))
            new = np.ones(len(at), np.int32)
            new[order[1:]] = (g[order[1:]] != g[order[:-1]]) | (row[order[1:]] != row[order[:-1]])
            return {"doc": columns["doc"].take(take), "mark": columns["mark"].take(take), "pos": pa.array(at - offsets[row]), "gram": pa.array(g.view(np.int64)), "lead": pa.array(lead.view(np.int64)), "new": pa.array(new)}

        return step

    return common.arrow_map(keyed, make, "doc long, mark long, pos long, gram long, lead long, new int")


def multikey_order(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The order of rows of big-endian words, and the number of equal leading bytes of each row and the one before it.

    A multikey quicksort that takes a word as a key: rows that tie so far are sorted by their next word, together for all
    groups of ties.
    """
    n, depth = words.shape
    order = np.arange(n)
    same = np.zeros(n, np.int64)  # leading bytes equal to the row before
    tied = np.zeros(n, np.int64)  # group of ties, -1: alone
    active = order.copy()
    for k in range(depth):
        if len(active) < 2:
            break
        word = words[order[active], k]
        rank = np.lexsort((word, tied[active]))
        order[active] = order[active][rank]
        word, group = word[rank], tied[active]  # groups are contiguous and keep their places
        new = np.ones(len(active), bool)
        new[1:] = (group[1:] != group[:-1]) | (word[1:] != word[:-1])
        inner = np.flatnonzero(new[1:] & (group[1:] == group[:-1])) + 1
        split = word[inner] ^ word[inner - 1]
        bits = np.zeros(len(inner), np.int64)
        for shift in (32, 16, 8):
            upper = (split >> np.uint64(64 - shift)) == 0
            bits += np.where(upper, shift, 0)
            split = np.where(upper, split << np.uint64(shift), split)
        same[active[inner]] = 8 * k + bits // 8
        keep = ~new
        same[active[keep]] = 8 * (k + 1)
        stay = keep.copy()
        stay[:-1] |= keep[1:]
        tied[active] = np.cumsum(new)
        active = active[stay]
    return order, same


def repeated_offsets(left: np.ndarray, right: np.ndarray, n_left: np.ndarray, n_right: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(repeated, leads, allowed), matrices of row and offset d: windows from d bytes left of an anchor; leads: first of its class.

    left holds reversed texts to the left of anchors, right the suffixes, zero-padded to whole words. Windows
    that would leave their text are not allowed and match nothing.
    """
    n = len(right)
    d = np.arange(min(left.shape[1], length) + 1)
    kind = np.int32 if n < 40_000 else np.int64
    sorted_sides = [multikey_order(side.view(">u8").astype(np.uint64).reshape(n, -1)) for side in (left, right)]
    allowed = (n_left[:, None] >= d) & (n_right[:, None] >= length - d)
    repeated, leads = np.zeros(allowed.shape, bool), np.zeros(allowed.shape, bool)
    for lo in range(0, len(d), COLUMNS):
        some = slice(lo, lo + COLUMNS)
        both = np.zeros((n, len(d[some])), kind)
        for (order, same), need in zip(sorted_sides, (d[some], length - d[some]), strict=True):
            classes = np.empty_like(both)
            classes[order] = np.cumsum(same[:, None] < need[None, :], axis=0, dtype=kind)
            both = both * kind(n + 1) + classes
        both = np.where(allowed[:, some], both, -1 - np.arange(n, dtype=kind)[:, None])
        rank = np.argsort(both, axis=0, kind="stable")
        inline = np.take_along_axis(both, rank, 0)
        twin = np.zeros(both.shape, bool)
        twin[1:] = inline[1:] == inline[:-1]
        np.put_along_axis(leads[:, some], rank, ~twin, 0)
        twin[:-1] |= twin[1:].copy()
        np.put_along_axis(repeated[:, some], rank, twin, 0)
    return repeated & allowed, leads & allowed, allowed


def _runs(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, first and last column of every run of set columns."""
    edge = np.zeros((mask.shape[0], mask.shape[1] + 2), np.int8)
    edge[:, 1:-1] = mask
    step = np.diff(edge, axis=1)
    row, first = np.nonzero(step == 1)
    return row, first, np.nonzero(step == -1)[1] - 1


def _padded(values: list[bytes], width: int, reverse: bool) -> np.ndarray:
    wide = -(-width // 8) * 8
    out = np.zeros((len(values), wide), np.uint8)
    for i, v in enumerate(values):
        at = np.frombuffer(v, np.uint8)
        out[i, : len(at)] = at[::-1] if reverse else at
    return out


SPANS = "doc long, mark long, start long, stop long, h1 long, h2 long"


def _compare(rows: dict, length: int, reach: int, hasher: Hasher, second: Hasher) -> pa.RecordBatch:
    """Spans of repeated windows among suffixes, and the open windows of crowded grams with their hashes; spans told before go through."""
    told = [i for i, b in enumerate(rows["before"]) if b is None]
    if told:
        names = ("doc", "mark", "pos", "gram")
        doc, mark, start, size = (np.array([rows[k][i] for i in told], np.int64) for k in names)
        spans = pa.RecordBatch.from_arrays([pa.array(doc), pa.array(mark), pa.array(start), pa.array(start + size), pa.nulls(len(told), pa.int64()), pa.nulls(len(told), pa.int64())], names=["doc", "mark", "start", "stop", "h1", "h2"])
        open_ = [i for i, b in enumerate(rows["before"]) if b is not None]
        if not open_:
            return spans
        rest = _compare({k: [v[i] for i in open_] for k, v in rows.items()}, length, reach, hasher, second)
        return pa.Table.from_batches([spans, rest]).combine_chunks().to_batches()[0]
    n_left = np.fromiter(map(len, rows["before"]), np.int64)
    n_right = np.fromiter(map(len, rows["after"]), np.int64)
    left, right = _padded(rows["before"], reach, True), _padded(rows["after"], length, False)
    repeated, leads, allowed = (x[:, : reach + 1] for x in repeated_offsets(left, right, n_left, n_right, length))
    row, first, last = _runs(repeated)
    pos = np.array(rows["pos"], np.int64)
    start, stop = pos[row] - last, pos[row] - first + length
    blank = np.zeros(len(row), np.int64)
    out = [(row, start, stop, blank, blank, np.zeros(len(row), bool))]
    crowded = np.flatnonzero(np.array(rows["crowded"]))
    for i in crowded:
        text = np.frombuffer(rows["before"][i] + rows["after"][i], np.uint8)
        d = np.flatnonzero(allowed[i])
        if not len(d):
            continue
        at = n_left[i] - d
        salt = np.uint64(rows["gram"][i] & _MASK) + d.astype(np.uint64) * np.uint64(_BASE)
        h1, h2 = (_mixed(h.windows(text, length)[at] ^ salt) for h in (hasher, second))
        single = ~repeated[i, d]
        told = leads[i, d]  # a class with twins here is told of once, by its first member, without a place
        start = np.where(single, pos[i] - d, -1)[told]
        out.append((np.full(told.sum(), i), start, start + length, h1[told].view(np.int64), h2[told].view(np.int64), np.ones(told.sum(), bool)))
    row, start, stop, h1, h2, pending = (np.concatenate(x) for x in zip(*out, strict=True))
    take = pa.array(row)
    doc, mark = pa.array(rows["doc"], pa.int64()).take(take), pa.array(rows["mark"], pa.int64()).take(take)
    return pa.RecordBatch.from_arrays([doc, mark, pa.array(start), pa.array(stop), pa.array(h1, mask=~pending), pa.array(h2, mask=~pending)], names=["doc", "mark", "start", "stop", "h1", "h2"])


def _keyed(documents: DataFrame) -> DataFrame:
    return documents.select(F.coalesce("doc_id", F.lit(-1)).alias("doc"), F.xxhash64("doc_id", "text").alias("mark"), "doc_id", F.coalesce("text", F.lit("")).alias("text"))


def repeated_spans(documents: DataFrame, length: int = LENGTH, gram: int = GRAM, crowd: int = CROWD) -> DataFrame:
    """(doc, mark, spans) with spans array<struct<start, stop>>, byte ranges of repeated windows, which may overlap."""
    if not 8 <= gram <= length:
        raise ValueError("gram must be from 8 to length")
    spark = documents.sparkSession
    ship(spark)
    keyed, reach = _keyed(documents), length - gram
    found = written(find_anchors(keyed.select("doc", "mark", "text"), length, gram), "suffix-anchors")
    # n counts texts: what a gram has more of in one text is nearly always the same context again, which goes on once
    often = found.groupBy("gram").agg(F.count(F.lit(1)).alias("times"), F.sum("new").alias("n")).where("times > 1").drop("times")
    often = written(often, "suffix-often")  # a table, so that a join with a very common gram can be split
    again = written(found.drop("new").join(often, "gram"), "suffix-again")
    discard(found, often)
    total = again.count()
    sample = again.select("lead", "gram").sample(min(1.0, SAMPLE / max(total, 1)), 42).toPandas() if total else None
    n_buckets = max(1, min(1 << 16, total // 4096))
    if sample is not None and len(sample):
        sample = sample.sort_values(["lead", "gram"]).to_numpy()
        cuts = sample[np.linspace(0, len(sample) - 1, n_buckets + 1).astype(int)[1:-1]]
    else:
        cuts = np.zeros((0, 2), np.int64)
    cut_lead, cut_gram = cuts[:, 0].tolist(), cuts[:, 1].tolist()

    places = again.groupBy("doc", "mark").agg(F.collect_set(F.struct("pos", "gram", "lead", "n")).alias("places"))

    def make():
        from bisect import bisect_right

        splitters = list(zip(cut_lead, cut_gram, strict=True))

        met: dict[bytes, tuple | None] = {}  # contexts of this task so far, and where the first one stands until a second comes

        def step(columns: dict) -> dict:
            out = {k: [] for k in ("doc", "mark", "pos", "gram", "bucket", "crowded", "before", "after")}

            def put(*values):
                for k, v in zip(out, values, strict=True):
                    out[k].append(v)

            def whole(doc, mark, pos, left, right):
                """All windows around this place are repeated: told as a span, with its length in place of the gram."""
                if left + right >= length:
                    put(doc, mark, pos - left, left + right, -1 - (pos & 4095), False, None, None)

            for doc, mark, text, where in zip(columns["doc"].to_pylist(), columns["mark"].to_pylist(), columns["text"], columns["places"], strict=True):
                data = text.as_py().encode("utf-8", "surrogatepass")
                for p in where.as_py():
                    pos = p["pos"]
                    before, after = data[max(0, pos - reach) : pos], data[pos : pos + length]
                    digest = hashlib.blake2b(before + len(before).to_bytes(4, "big") + after, digest_size=16).digest()
                    if digest in met:  # one of equal contexts goes on, to meet those of other tasks
                        if met[digest]:
                            whole(*met[digest])
                            met[digest] = None
                        whole(doc, mark, pos, len(before), len(after))
                        continue
                    if len(met) >= MEMORY:  # what comes again is told in its bucket
                        met.clear()
                    met[digest] = (doc, mark, pos, len(before), len(after))
                    crowded = p["n"] > crowd
                    bucket = bisect_right(splitters, (p["lead"], p["gram"]))
                    if crowded:
                        part = int.from_bytes(digest[:6], "big") % -(-p["n"] // crowd)
                        bucket = int.from_bytes(hashlib.blake2b(f"{p['gram']} {part}".encode(), digest_size=7).digest(), "big") + (1 << 17)
                    put(doc, mark, pos, p["gram"], bucket, crowded, before, after)
            return out

        return step

    suffixes = common.arrow_map(
        keyed.select("doc", "mark", "text").join(places, ["doc", "mark"]), make, "doc long, mark long, pos long, gram long, bucket long, crowded boolean, before binary, after binary", rows=128
    )
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    suffixes = suffixes.repartition(parts, "bucket").sortWithinPartitions("bucket", "gram")

    def compare(batches):
        hasher, second = Hasher(length + reach), Hasher(length + reach)
        second.values = _mixed(second.values)
        held: dict[str, list] = {}
        for batch in (whole.slice(lo, ROWS) for whole in batches for lo in range(0, whole.num_rows, ROWS)):
            rows = batch.to_pydict()
            held = {k: held.get(k, []) + v for k, v in rows.items()}
            while len(held["gram"]) > ROWS:
                cut = _whole_groups(held, ROWS)
                if not cut:
                    break
                yield _compare({k: v[:cut] for k, v in held.items()}, length, reach, hasher, second)
                held = {k: v[cut:] for k, v in held.items()}
        if held and held["gram"]:
            yield _compare(held, length, reach, hasher, second)

    spans = written(suffixes.mapInArrow(common.frugal(compare), SPANS), "suffix-spans")
    discard(again)
    met = spans.where("h1 IS NOT NULL").groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("times"), F.collect_list(F.when(F.col("start") >= 0, F.struct("doc", "mark", "start", "stop"))).alias("own")).where("times > 1")
    across = met.select(F.explode("own").alias("o")).select("o.*")
    spans = spans.where("h1 IS NULL").select("doc", "mark", "start", "stop").unionByName(across)
    return spans.groupBy("doc", "mark").agg(F.collect_set(F.struct("start", "stop")).alias("spans"))


def _whole_groups(rows: dict, most: int) -> int:
    """The largest cut at a border of (bucket, gram) at or before most, or else the first after it; 0 if there is none."""
    bucket, gram = rows["bucket"], rows["gram"]
    differs = [i for i in range(1, len(gram)) if gram[i] != gram[i - 1] or bucket[i] != bucket[i - 1]]
    return max((i for i in differs if i <= most), default=next((i for i in differs if i > most), 0))


def without(data: bytes, spans: list[tuple[int, int]]) -> tuple[bytes, list[tuple[int, int]]]:
    """What is left of data, and the maximal removed runs."""
    runs: list[list[int]] = []
    for a, b in sorted(spans):
        if runs and a <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], b)
        else:
            runs.append([a, b])
    kept, at = [], 0
    for a, b in runs:
        kept.append(data[at:a])
        at = b
    kept.append(data[at:])
    return b"".join(kept), [(a, b) for a, b in runs]


def remove_repeats(documents: DataFrame, length: int = LENGTH, gram: int = GRAM, crowd: int = CROWD) -> DataFrame:
    """(doc_id, kept binary, n_bytes, n_removed, n_spans, kept_sha256) for every row of documents(doc_id, text).

    Null texts count as empty; texts under `length` bytes stay whole. Rows that agree in doc_id and text are two documents,
    which repeat each other. What is left may end within a character, so it is bytes. An empty table gives no rows.
    """
    keyed = _keyed(documents)
    joined = keyed.join(repeated_spans(documents, length, gram, crowd), ["doc", "mark"], "left")

    def make():
        def step(columns: dict) -> dict:
            out = {k: [] for k in ("kept", "n_bytes", "n_removed", "n_spans", "kept_sha256")}
            for text, spans in zip(columns["text"], columns["spans"], strict=True):
                data = text.as_py().encode("utf-8", "surrogatepass")
                kept, runs = without(data, [(s["start"], s["stop"]) for s in spans.as_py() or ()])
                for k, v in (("kept", kept), ("n_bytes", len(data)), ("n_removed", len(data) - len(kept)), ("n_spans", len(runs)), ("kept_sha256", hashlib.sha256(kept).hexdigest())):
                    out[k].append(v)
            return out | {"doc_id": columns["doc_id"]}

        return step

    return common.arrow_map(joined.select("doc_id", "text", "spans"), make, "doc_id long, kept binary, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def op10_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of all documents.

    Null texts count as empty; texts under 400 bytes lose nothing. Repeated rows are documents that repeat each other. An empty table
    gives no rows. Other columns are left aside.
    """
    return remove_repeats(common.table(spark, sf_dir, "documents", "doc_id", "text")).drop("kept")
