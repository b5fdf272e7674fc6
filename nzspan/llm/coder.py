"""Token ids in blocks, coded by an adaptive context-mixing range coder.

A block holds the ids of whole documents. It resets the model and carries checksums, so it can be read alone. Its ids are
dealt to lanes of equal length that move in step; every step codes one id of each lane, and the
model learns from all of them. Lanes are many and short, so that a step's arrays are long beside what a call of numpy costs. An id is coded as one symbol, and plain bits where the symbol leaves some open:

- 0: the id that last followed the two ids before;
- 1: the id that last followed the one id before;
- 2 + n: an id whose rank by frequency in the block has n bits, of which the lower n - 1 are plain.

Three models predict the symbol, each by adaptive frequencies: of order 0 (one table), of order 1 (a table for each
bit length of the id before and trust in what followed it) and of order 2 (for the bit lengths of the two ids
before, the trust in what followed both, and whether the two followers agree). The range coder codes with the mixture of the three.
Every lane has its own weights: after each symbol a model's weight is multiplied by the chance it gave, and a share of all weight is
dealt out evenly, so that a model that was poor can return. Mixture, weights and tables are whole numbers or plain sums, products and quotients, which
the reader repeats exactly. Lanes are coded by vector arithmetic.

Layout of a payload, numbers little-endian:
magic 4 bytes, version u8, lane length u32, ids u64, distinct u32, ids' crc32 u32, lanes u32,
distinct ids by rank as u32, the first four 16-bit words of each lane, then the lanes' further words in the order in which a
reader that moves all lanes in step takes them; last the crc32 of all before it, u32.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

MAGIC, VERSION = b"CMRC", 3
LANE = 256
HEAD = struct.Struct("<4sBIQIII")
SCALE = 12  # bits of the frequencies' total
CLASSES = 34  # two predictions, and ranks of 0 to 31 bits
WIDTHS, HALVES = 32, 16  # bit lengths that order 1, and pairs of bit lengths that order 2, tells apart
FIRST = np.array([0, 1, 1 + 4 * WIDTHS, 1 + 4 * WIDTHS + 8 * HALVES * HALVES])  # where the tables of each order begin, and their end
WEIGHT, SHARED = 16, 5  # bits of the weights' total; a share of 1 in 2 ** SHARED is dealt out evenly
SETTLED, EVERY = 8, 16  # tables are brought up to date every step until this one, and then every so many steps
HASH = 18
WORDS = 4  # 16-bit words of a lane that a reader holds at once
_TOP, _LOW = np.uint64(1 << 48), np.uint64(1 << 32)
_U = np.uint64


class Damaged(ValueError):
    """A block that fails its checksum or its layout."""


class Predictor:
    """The adaptive state of a block: predictions with their confidence, frequency tables of three orders, and weights."""

    def __init__(self, lanes: int, classes: int = CLASSES):
        self.classes = classes  # no symbol reaches this
        self.follow1, self.follow2 = np.zeros(1 << HASH, np.int32), np.zeros(1 << HASH, np.int32)  # four times the follower, and trust in it
        self.counts = np.full((FIRST[-1], CLASSES), 0.05)
        self.counts[:, 2:] += 0.05
        self.cumulative = np.zeros((FIRST[-1], CLASSES + 1), np.int32)
        self.flat = self.cumulative.ravel()
        self.last1, self.last2 = np.zeros(lanes, np.int64), np.zeros(lanes, np.int64)
        self.long1, self.long2 = np.zeros(lanes, np.int32), np.zeros(lanes, np.int32)
        self.weights = np.full((3, lanes), (1 << WEIGHT) // 3, np.int32)
        self.weights[0] += (1 << WEIGHT) - self.weights.sum(axis=0, dtype=np.int32)
        self.steps, self.recent = 0, []
        self.refresh(np.arange(FIRST[-1]))

    def refresh(self, some: np.ndarray) -> None:
        """Bring the cumulative frequencies of some tables up to date; every symbol keeps a frequency of one at least."""
        spare = (1 << SCALE) - CLASSES
        grown = np.cumsum(self.counts[some], axis=1)
        grown *= spare / grown[:, -1:]
        grown[:, -1] = spare
        self.cumulative[some, 1:] = grown.astype(np.int32) + np.arange(1, CLASSES + 1, dtype=np.int32)

    def look(self, n: int) -> None:
        """Predictions for the first n lanes."""
        last1, last2 = self.last1[:n], self.last2[:n]
        self.at1 = last1 & ((1 << HASH) - 1)
        self.at2 = ((last1 * 0x1E3779B97F4A7C15 + last2 * 0x3F58476D1CE4E5B9) >> 40) & ((1 << HASH) - 1)
        self.held1, self.held2 = self.follow1.take(self.at1), self.follow2.take(self.at2)
        self.guess1, self.guess2 = self.held1 >> 2, self.held2 >> 2
        self.trust1, self.trust2 = self.held1 & 3, self.held2 & 3
        long1, long2 = self.long1[:n], self.long2[:n]
        order1 = (long1 << 2) + (self.trust1 + FIRST[1])
        order2 = ((long1 >> 1) * HALVES + (long2 >> 1) << 2) + self.trust2
        order2 = (order2 << 1) + (self.guess1 == self.guess2) + FIRST[2]
        self.tables = (order1, order2)
        self.bases = [t * np.int32(CLASSES + 1) for t in self.tables]
        self.shares = self.weights[:, :n]

    def _terms(self, symbol: np.ndarray) -> list[np.ndarray]:
        """Cumulative frequency below a symbol of each lane, by model."""
        return [self.flat.take(symbol), self.flat.take(self.bases[0] + symbol), self.flat.take(self.bases[1] + symbol)]

    def _mixed(self, terms: list[np.ndarray]) -> np.ndarray:
        total = self.shares[0] * terms[0]
        for k in (1, 2):
            total += self.shares[k] * terms[k]
        total >>= WEIGHT
        return total

    def mixture(self, symbol: np.ndarray) -> np.ndarray:
        """Cumulative frequency below a symbol of each lane, of the weighted mixture of the three models."""
        return self._mixed(self._terms(symbol))

    def span(self, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        """The mixture below and above the symbols, and the frequencies that each model gives them."""
        lower, upper = self._terms(symbol), self._terms(symbol + 1)
        return self._mixed(lower), self._mixed(upper), [u - v for u, v in zip(upper, lower, strict=True)]

    def seek(self, target: np.ndarray) -> np.ndarray:
        """The symbols whose frequencies hold the targets."""
        found = np.zeros(len(target), np.int32)
        step = 1 << ((self.classes - 1).bit_length() - 1)
        while step:
            middle = np.minimum(found + np.int32(step), self.classes)
            found += (target >= self.mixture(middle)) * np.int32(step)
            step >>= 1
        return np.minimum(found, self.classes - 1)

    def find(self, target: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The symbols whose frequencies hold the targets, and the cumulative frequencies below and above them."""
        symbol = self.seek(target)
        return symbol, self.mixture(symbol), self.mixture(symbol + 1)

    def learn(self, rank: np.ndarray, bits: np.ndarray, symbol: np.ndarray, given: list[np.ndarray] | None = None) -> None:
        """Take in the symbols; given: what span said of them."""
        n = len(rank)
        given = given or self.span(symbol)[2]
        fresh = (rank << 2).astype(np.int32)
        for at, held, guess, trust, follow in ((self.at1, self.held1, self.guess1, self.trust1, self.follow1), (self.at2, self.held2, self.guess2, self.trust2, self.follow2)):
            # of lanes that share a slot the last one counts
            follow[at] = np.where(guess == rank, held + (trust < 3), np.where(trust > 0, held - 1, fresh))
        # weights: as much more as the model gave the symbol
        given = [g * w for g, w in zip(given, self.shares, strict=True)]
        shared = (1 << WEIGHT) >> SHARED
        times = float((1 << WEIGHT) - shared) / (given[0] + given[1] + given[2])
        for k in (1, 2):
            self.weights[k, :n] = given[k] * times
            self.weights[k, :n] += shared // 3
        self.weights[0, :n] = (1 << WEIGHT) - self.weights[1, :n] - self.weights[2, :n]
        self.recent += [symbol, *(t * CLASSES + symbol for t in self.tables)]
        self.steps += 1
        if self.steps < SETTLED or self.steps % EVERY == 0:
            times = np.bincount(np.concatenate(self.recent), minlength=self.counts.size).reshape(self.counts.shape)
            some = np.flatnonzero(times.any(axis=1))
            self.counts[some] += times[some]
            full = some[self.counts[some].sum(axis=1) > 65536]
            self.counts[full] *= 0.5
            self.refresh(some)
            self.recent = []
        self.last2[:n], self.long2[:n] = self.last1[:n], self.long1[:n]
        self.last1[:n], self.long1[:n] = rank, bits


def bit_length(x: np.ndarray) -> np.ndarray:
    """Bits of a number: 0 for 0, 1 for 1, 2 for 2 and 3, and so on."""
    return np.frexp(x.astype(float))[1].astype(np.int64)


def _steps(n: int, lane: int):
    """Lane starts, and how many lanes there are; the last lane may be shorter."""
    lanes = max(1, -(-n // lane))
    return lanes, n - (lanes - 1) * lane


def _ranked(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct ids by falling frequency, and each id's place among them."""
    if not len(ids):
        return ids, np.zeros(0, np.int32)
    if ids.max() < 1 << 20:
        counts = np.bincount(ids)
        distinct = np.flatnonzero(counts)
        by_rank = distinct[np.argsort(-counts[distinct], kind="stable")]
        place = np.zeros(len(counts), np.int32)
        place[by_rank] = np.arange(len(by_rank))
        return by_rank.astype(np.uint32), place.take(ids)
    distinct, inverse, counts = np.unique(ids, return_inverse=True, return_counts=True)
    order = np.argsort(-counts, kind="stable")
    place = np.empty(len(distinct), np.int32)
    place[order] = np.arange(len(distinct))
    return distinct[order], place.take(inverse)


def _parts_of_ranks(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of ranks below n: bit length, plain bits, and their value."""
    ranks = np.arange(max(n, 1))
    bits = bit_length(ranks)
    plain = np.maximum(bits - 1, 0)
    return bits.astype(np.int32), plain.astype(np.uint8), (ranks & ((1 << plain) - 1)).astype(np.int32)


class Stream:
    """Intervals of the lanes. turn() makes room in those that ran short of it, a 16-bit word at a time, the same for writer and reader."""

    def __init__(self, lanes: int):
        self.low, self.width = np.zeros(lanes, np.uint64), np.full(lanes, 0xFFFFFFFFFFFFFFFF, np.uint64)

    def turn(self, n: int, word) -> None:
        """word(at, low): called with the lanes that pass on a word, and their intervals' lower ends."""
        low, width = self.low[:n], self.width[:n]
        at = np.flatnonzero(((low ^ (low + width)) < _TOP) | (width < _LOW))
        if not len(at):
            return
        some, wide = low.take(at), width.take(at)
        while True:
            straddles = (some ^ (some + wide)) >= _TOP
            if straddles.any():
                wide = np.where(straddles, (~some + _U(1)) & (_LOW - _U(1)), wide)
            word(at, some)
            some, wide = some << _U(16), wide << _U(16)
            low[at], width[at] = some, wide
            more = np.flatnonzero(((some ^ (some + wide)) < _TOP) | (wide < _LOW))
            if not len(more):
                return
            at, some, wide = at.take(more), some.take(more), wide.take(more)


def encode_block(ids: np.ndarray, lane: int = LANE) -> bytes:
    """The payload of a block of ids, any unsigned 32-bit integers; none are fine."""
    ids = np.ascontiguousarray(ids, np.uint32)
    distinct, ranks = _ranked(ids)
    if len(distinct) > 1 << 29:
        raise ValueError("too many different ids for one block")
    lanes, short = _steps(len(ids), lane)
    grid = np.zeros(lanes * lane, np.int32)
    grid[: len(ids)] = ranks
    grid = np.ascontiguousarray(grid.reshape(lanes, lane).T)
    bits_of, plain_of, rest_of = _parts_of_ranks(len(distinct))
    model, stream = Predictor(lanes, int(bits_of[-1]) + 3), Stream(lanes)
    places, words = [], []

    def word(at: np.ndarray, low: np.ndarray) -> None:
        places.append(at.astype(np.int32))
        words.append((low >> _U(48)).astype(np.uint16))

    for t in range(min(lane, len(ids))):
        n = lanes if t < short else lanes - 1
        if not n:
            break
        model.look(n)
        rank = grid[t, :n]
        bits = bits_of.take(rank)
        symbol = np.where(rank == model.guess2, np.int32(0), np.where(rank == model.guess1, np.int32(1), bits + np.int32(2)))
        from_, to, given = model.span(symbol)
        low, width = stream.low[:n], stream.width[:n]
        part = width >> _U(SCALE)
        low += part * from_.astype(np.uint64)
        part *= (to - from_).astype(np.uint64)
        told = symbol > 1
        part >>= plain_of.take(rank) * told
        low += part * (rest_of.take(rank) * told).astype(np.uint64)
        width[:] = part
        stream.turn(n, word)
        model.learn(rank, bits, symbol, given)
    first, later = _in_reading_order(lanes, places, words, stream.low)
    body = HEAD.pack(MAGIC, VERSION, lane, len(ids), len(distinct), zlib.crc32(ids.astype("<u4").tobytes()), lanes)
    body += distinct.astype("<u4").tobytes() + first.astype("<u2").tobytes() + later.astype("<u2").tobytes()
    return body + struct.pack("<I", zlib.crc32(body))


def _in_reading_order(lanes: int, places: list, words: list, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first words of each lane, and the others where a reader takes them: when a lane passes on a word, it reads the one WORDS later."""
    lane_of = np.concatenate([*places, np.zeros(0, np.int32)])
    word = np.concatenate([*words, np.zeros(0, np.uint16)])
    order = np.argsort(lane_of.astype(np.uint16) if lanes <= 1 << 16 else lane_of, kind="stable")
    ends = WORDS * np.arange(lanes) + np.cumsum(np.bincount(lane_of, minlength=lanes))
    at = np.arange(len(order)) + WORDS * lane_of[order]  # words of a lane lie together, the last ones after those passed on
    whole = np.zeros(len(order) + WORDS * lanes, np.uint16)
    whole[at] = word[order]
    for k in range(WORDS):
        whole[ends + k] = (low >> _U(48 - 16 * k)).astype(np.uint16)
    later = np.empty(len(order), np.uint16)
    later[order] = whole[at + WORDS]
    starts = np.concatenate([[0], ends[:-1] + WORDS])
    return whole[starts[:, None] + np.arange(WORDS)], later


def decode_block(payload: bytes) -> np.ndarray:
    """The ids of a payload; Damaged if it is not whole."""
    if len(payload) < HEAD.size + 4 or zlib.crc32(payload[:-4]) != struct.unpack("<I", payload[-4:])[0]:
        raise Damaged("a block fails its checksum")
    magic, version, lane, count, n_distinct, crc, lanes = HEAD.unpack_from(payload)
    if magic != MAGIC or version != VERSION:
        raise Damaged("not a block of this format")
    at = HEAD.size
    distinct = np.frombuffer(payload, "<u4", n_distinct, at)
    first = np.frombuffer(payload, "<u2", WORDS * lanes, at + 4 * n_distinct).reshape(lanes, WORDS)
    at += 4 * n_distinct + 2 * WORDS * lanes
    later = np.frombuffer(payload, "<u2", (len(payload) - 4 - at) // 2, at)
    code = np.zeros(lanes, np.uint64)
    for k in range(WORDS):
        code = (code << _U(16)) | first[:, k]
    _, short = _steps(count, lane)
    grid = np.zeros((lane, lanes), np.int32)
    bits_of, plain_of, _rest = _parts_of_ranks(n_distinct)
    model, stream = Predictor(lanes, int(bits_of[-1]) + 3), Stream(lanes)
    plain_of_symbol = np.maximum(np.arange(CLASSES) - 3, 0)
    leading_of_symbol = (np.arange(CLASSES) > 2) * (1 << plain_of_symbol)
    plain_of_symbol = plain_of_symbol.astype(np.uint8)
    got = 0

    def word(at: np.ndarray, low: np.ndarray) -> None:
        nonlocal got
        if got + len(at) > len(later):
            raise Damaged("a block ends early")
        code[at] = (code.take(at) << _U(16)) | later[got : got + len(at)]
        got += len(at)

    for t in range(min(lane, count)):
        n = lanes if t < short else lanes - 1
        if not n:
            break
        model.look(n)
        low, width = stream.low[:n], stream.width[:n]
        part = width >> _U(SCALE)
        target = np.minimum((code[:n] - low) // part, _U((1 << SCALE) - 1)).astype(np.int32)
        symbol = model.seek(target)
        from_, to, given = model.span(symbol)
        low += part * from_.astype(np.uint64)
        part *= (to - from_).astype(np.uint64)
        plain = plain_of_symbol.take(symbol)
        part >>= plain
        rank = np.where(symbol == 0, model.guess2, model.guess1)
        told = np.flatnonzero(symbol > 1)
        some, wide = low.take(told), part.take(told)
        rest = np.minimum((code.take(told) - some) // wide, (_U(1) << plain.take(told)) - _U(1))
        low[told] = some + wide * rest
        rank[told] = leading_of_symbol.take(symbol.take(told)) + rest.astype(np.int64)
        width[:] = part
        if rank.max() >= n_distinct:
            raise Damaged("a block holds ids that it does not list")
        grid[t, :n] = rank
        stream.turn(n, word)
        model.learn(rank, bits_of.take(rank), symbol, given)
    ids = distinct[np.ascontiguousarray(grid.T).reshape(-1)[:count]] if count else np.zeros(0, "<u4")
    if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
        raise Damaged("a block's ids fail their checksum")
    return ids.astype(np.uint32)
