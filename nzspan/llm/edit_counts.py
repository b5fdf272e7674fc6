"""Token counts that follow edits, by a segment tree over each document's pre-tokens.

Byte-pair encoding never crosses a pre-token, so a text's count is a sum over pre-tokens. Leaves hold the characters and
tokens of some sixty-four pre-tokens each, inner nodes the sums. An edit re-encodes from the leaf that holds the character a
few places before it, as the pattern looks ahead that far, until a pre-token ends where an old leaf ends beyond the
edit: from there on the pattern finds what it found before. Then only the sums above the replaced leaves change.
"""

from __future__ import annotations

import base64

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nzspan.session import ship

from . import common
from .pieces import _lists

LEAF, CONTEXT = 64, 8
#: Remembered pre-tokens of a worker.
MEMORY = 500_000


def default_ranks() -> tuple[str, str]:
    """(path of the byte-pair ranks, pre-token pattern)."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


class Counter:
    """Pre-tokens of a text and the number of tokens of each."""

    def __init__(self, ranks: bytes, pattern: str):
        import regex
        import tiktoken

        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.splitlines()) if a}
        self.library = tiktoken.Encoding("counts", pat_str=pattern, mergeable_ranks=table, special_tokens={})
        self.pattern = regex.compile(pattern)
        self.known: dict[str, int] = {}

    def count(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            if len(self.known) >= MEMORY:
                self.known.clear()
            n = self.known[piece] = len(self.library.encode_ordinary(piece))
        return n

    def leaves(self, text: str) -> tuple[list[int], list[int]]:
        """(characters, tokens) of each leaf of a text."""
        pieces = self.pattern.findall(text)
        known, count = self.known.get, self.count
        tokens = [known(p) or count(p) for p in pieces]
        sizes = list(map(len, pieces))
        cuts = range(0, len(pieces), LEAF)
        return [sum(sizes[i : i + LEAF]) for i in cuts], [sum(tokens[i : i + LEAF]) for i in cuts]


class Tree:
    """Sums of characters and tokens over the leaves of one document."""

    def __init__(self, chars: list[int], tokens: list[int]):
        self.build(list(chars), list(tokens))

    def build(self, chars: list[int], tokens: list[int]) -> None:
        self.width = 1 << max(0, (len(chars) - 1).bit_length())
        self.used = len(chars)
        self.chars, self.tokens = ([0] * self.width + values + [0] * (self.width - len(values)) for values in (chars, tokens))
        for i in range(self.width - 1, 0, -1):
            self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
            self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    @property
    def n_tokens(self) -> int:
        return self.tokens[1]

    @property
    def n_chars(self) -> int:
        return self.chars[1]

    def leaves(self) -> tuple[list[int], list[int]]:
        lo, hi = self.width, self.width + self.used
        return self.chars[lo:hi], self.tokens[lo:hi]

    def find(self, place: int) -> tuple[int, int]:
        """(leaf, where it starts) of the leaf that holds this character; the last used one for the text's end."""
        if place >= self.n_chars:
            leaf = self.width + max(0, self.used - 1)
            return leaf - self.width, self.n_chars - self.chars[leaf]
        i, start = 1, 0
        while i < self.width:
            i *= 2
            if place - start >= self.chars[i]:
                start += self.chars[i]
                i += 1
        return i - self.width, start

    def put(self, first: int, last: int, chars: list[int], tokens: list[int]) -> None:
        """New values for leaves first..last, and new sums above them."""
        for k, (c, t) in enumerate(zip(chars, tokens, strict=True)):
            self.chars[self.width + first + k], self.tokens[self.width + first + k] = c, t
        lo, hi = (self.width + first) // 2, (self.width + last) // 2
        while lo:
            for i in range(lo, hi + 1):
                self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
                self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]
            lo, hi = lo // 2, hi // 2

    def replace(self, first: int, last: int, chars: list[int], tokens: list[int]) -> None:
        """Leaves first..last give way to the given pre-tokens, dealt out evenly; too many for them make a new tree of the same leaves."""
        room = last - first + 1
        each = max(1, -(-len(chars) // room))
        cuts = range(0, room * each, each)
        if each <= 4 * LEAF:
            self.put(first, last, [sum(chars[i : i + each]) for i in cuts], [sum(tokens[i : i + each]) for i in cuts])
            return
        old_chars, old_tokens = self.leaves()
        new = range(0, len(chars), LEAF)
        old_chars[first : last + 1] = [sum(chars[i : i + LEAF]) for i in new]
        old_tokens[first : last + 1] = [sum(tokens[i : i + LEAF]) for i in new]
        self.build(old_chars, old_tokens)


def edit(counter: Counter, tree: Tree, text: str, at: int, removed: int, inserted: str) -> tuple[str, int]:
    """(new text, characters encoded anew): text with `removed` characters from `at` on replaced; the tree follows. Places beyond the text mean its end."""
    at = min(max(at, 0), len(text))
    stop = min(len(text), at + max(removed, 0))
    new = text[:at] + inserted + text[stop:]
    shift = len(new) - len(text)
    if not tree.used:
        tree.build(*counter.leaves(new))
        return new, len(new)
    first, start = tree.find(max(0, at - CONTEXT))
    last, last_start = tree.find(max(stop - 1, 0))
    last = max(first, last)
    border = (last_start if last > first else start) + tree.chars[tree.width + last]
    while border < stop and last + 1 < tree.used:
        last += 1
        border += tree.chars[tree.width + last]
    sizes, tokens, here = [], [], start
    for match in counter.pattern.finditer(new, start):
        piece = match.group()
        here = match.end()
        sizes.append(len(piece))
        tokens.append(counter.count(piece))
        while border + shift < here and last + 1 < tree.used:
            last += 1
            border += tree.chars[tree.width + last]
        if here == border + shift and here >= at + len(inserted):
            break
    tree.replace(first, last, sizes, tokens)
    return new, here - start


def count_documents(documents: DataFrame, ranks: str | None = None, pattern: str | None = None) -> DataFrame:
    """(row..., n_tokens, leaf_chars array<int>, leaf_tokens array<int>) for every row of documents, text among its columns.

    Null and empty texts have no leaves and count 0. Columns of the input with these names give way. An empty table gives no rows.
    """
    ship(documents.sparkSession)
    path, default = default_ranks()
    with open(ranks or path, "rb") as file:
        table = file.read()
    keep = [f for f in documents.schema.fields if f.name not in ("n_tokens", "leaf_chars", "leaf_tokens")]

    def make():
        counter = Counter(table, pattern or default)

        def step(columns: dict) -> dict:
            found = [counter.leaves(t.as_py() or "") for t in columns["text"]]
            return {f.name: columns[f.name] for f in keep} | {"n_tokens": [sum(t) for _, t in found], "leaf_chars": _lists([c for c, _ in found]), "leaf_tokens": _lists([t for _, t in found])}

        return step

    leaf = T.ArrayType(T.IntegerType())
    schema = T.StructType([*keep, T.StructField("n_tokens", T.LongType()), T.StructField("leaf_chars", leaf), T.StructField("leaf_tokens", leaf)])
    return common.arrow_map(documents.select(*[f.name for f in keep]), make, schema)


def recount(counted: DataFrame, ranks: str | None = None, pattern: str | None = None) -> DataFrame:
    """counted with edits(array<struct<at, removed, inserted>>) made one after the other.

    text, leaf_chars, leaf_tokens and n_tokens are those after the edits; n_encoded is the number of characters encoded anew.
    Null edits are none.
    """
    ship(counted.sparkSession)
    path, default = default_ranks()
    with open(ranks or path, "rb") as file:
        table = file.read()
    fields = [f for f in counted.schema.fields if f.name not in ("edits", "n_encoded")]
    changed = {"text", "n_tokens", "leaf_chars", "leaf_tokens"}

    def make():
        counter = Counter(table, pattern or default)

        def step(columns: dict) -> dict:
            out = {k: [] for k in ("text", "n_tokens", "leaf_chars", "leaf_tokens", "n_encoded")}
            for text, chars, tokens, edits in zip(*(columns[c] for c in ("text", "leaf_chars", "leaf_tokens", "edits")), strict=True):
                text, tree, encoded = text.as_py() or "", Tree(chars.as_py() or [], tokens.as_py() or []), 0
                for e in edits.as_py() or ():
                    text, n = edit(counter, tree, text, e["at"], e["removed"], e["inserted"] or "")
                    encoded += n
                chars, tokens = tree.leaves()
                for k, v in zip(out, (text, tree.n_tokens, chars, tokens, encoded), strict=True):
                    out[k].append(v)
            out |= {k: _lists(out[k]) for k in ("leaf_chars", "leaf_tokens")}
            return {f.name: columns[f.name] for f in fields if f.name not in changed} | out

        return step

    return common.arrow_map(counted, make, T.StructType([*fields, T.StructField("n_encoded", T.LongType())]))


def op3_edit_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, edited_tokens, edited_chars, n_encoded, n_leaves of all documents.

    Each text is edited three times: sixteen characters from two thirds on give way to its first twenty-four, a word comes in at one
    third, and the last eight characters go. Null texts count as empty; repeated rows are counted each; an empty table gives no rows.
    """
    documents = common.table(spark, sf_dir, "documents", "doc_id", "text").withColumn("text", F.coalesce("text", F.lit("")))
    counted = count_documents(documents).withColumnRenamed("n_tokens", "before").withColumn("n_tokens", F.col("before"))
    n = F.length("text")
    one = lambda at, removed, inserted: F.struct(at.cast("int").alias("at"), removed.cast("int").alias("removed"), inserted.alias("inserted"))
    head = F.substring("text", 1, 24)
    third = F.floor(n / 3)
    # lengths after the edits so far place the next one
    now = n - F.least(F.lit(16), n - F.floor(n * 2 / 3)) + F.length(head) + 7
    edits = F.array(one(F.floor(n * 2 / 3), F.lit(16), head), one(third, F.lit(0), F.lit(" edited")), one(F.greatest(now - 8, F.lit(0)), F.lit(8), F.lit("")))
    edited = recount(counted.withColumn("edits", edits))
    return edited.select("doc_id", F.col("before").alias("n_tokens"), F.col("n_tokens").alias("edited_tokens"), F.length("text").cast("long").alias("edited_chars"), "n_encoded", F.size("leaf_chars").alias("n_leaves"))
