"""Document fingerprints from spot signatures, in DataFrame functions only.

A signature starts at a common word, the anchor, and goes on with the next content words, those that are no
anchors. Its words say little alone, so chains of them are told by where prose is prose. A document is the
set of its signatures' hashes; its fingerprint holds the number of signatures and all their hashes. Two sets are
compared by their exact Jaccard. For near-duplicates,
sets are partitioned by length, as sets whose lengths differ too much cannot be alike, and only those compared that
share one of their rarest signatures.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nzspan.session import written

from . import common

#: Common words of English, French, German and Spanish, the anchors.
ANCHORS = (
    "a an and are as at be by for from in is it of on or that the this to was with "
    "de des du en et est la le les pas pour que qui un une "
    "als auf das dem den der die ein eine ist mit nicht und von zu "
    "con del el es las los no para por se una y"
).split()
#: Content words of a chain.
CHAIN = 2
_MARK = "\u0001"


def signature_hashes(text: Column, anchors: tuple[str, ...] | list[str] = tuple(ANCHORS), chain: int = CHAIN) -> tuple[Column, Column]:
    """(segments, hashes of segments): the text cut at its anchors, and a function's worth of columns to hash the chains.

    Words are told apart by white space, and compared in lower case. A segment is an anchor with the content words up to
    the next anchor; a chain that needs more words takes them from the segments that follow.
    """
    by_first: dict[str, list[str]] = {}
    for word in sorted(set(anchors)):
        by_first.setdefault(word[0], []).append(re.escape(word[1:]))
    choice = "|".join(f"{re.escape(first)}(?:{'|'.join(rest)})" for first, rest in sorted(by_first.items()))
    flat = F.concat(F.lit(" "), F.translate(F.lower(text), "\t\n\x0b\x0c\r" + _MARK, "      "), F.lit(" "))
    segments = F.split(F.regexp_replace(flat, f" +({choice})(?= )", f"{_MARK}$1"), _MARK)
    return flat, segments


def _with_set(df: DataFrame, text: str, out: str, anchors, chain: int) -> DataFrame:
    """df with out, the sorted distinct 32-bit hashes of a text column's signatures; texts without anchors use their words."""
    flat, segments = signature_hashes(F.col(text), anchors, chain)
    df = df.withColumn("_segments", segments)
    # what follows the anchor of each segment
    after = lambda s: F.when(F.instr(s, " ") > 0, F.ltrim(F.substr(s, F.instr(s, " ") + F.lit(1)))).otherwise("")
    df = df.withColumn("_content", F.transform("_segments", after))

    def one(s: Column, i: Column) -> Column:
        more = [F.coalesce(F.get("_content", i + F.lit(k)), F.lit("")) for k in range(1, chain + 2)]
        words = F.regexp_replace(F.concat_ws(" ", s, *more), " +", " ")
        return F.when(i > 0, F.xxhash64(F.rtrim(F.substring_index(words, " ", chain + 1))))

    hashes = F.array_compact(F.transform("_segments", one))
    words = F.transform(F.filter(F.split(F.lower(F.col(text)), "[\\x20\\x09-\\x0D]+"), lambda w: w != ""), lambda w: F.xxhash64(w))
    df = df.withColumn("_hashes", hashes)
    df = df.withColumn("_hashes", F.when(F.size("_hashes") > 0, F.col("_hashes")).otherwise(words))
    small = F.transform("_hashes", lambda h: h.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int"))
    return df.withColumn(out, F.array_sort(F.array_distinct(small))).drop("_segments", "_content", "_hashes")


def with_sketch(df: DataFrame, text: str, size: str, sketch: str, anchors=tuple(ANCHORS), chain: int = CHAIN) -> DataFrame:
    """df with the number of a text column's signatures and all their hashes in order; null texts count as empty."""
    df = df.withColumn("_text", F.coalesce(F.col(text), F.lit("")))
    df = _with_set(df, "_text", sketch, anchors, chain)
    return df.withColumn(size, F.size(sketch)).drop("_text")


def fingerprint_text(size: Column, sketch: Column) -> Column:
    """Fingerprint as a string of hexadecimal digits: eight for the number of signatures, eight for each hash."""
    digits = lambda x: F.lpad(F.lower(F.hex(x)), 8, "0")
    return F.concat(digits(size), F.array_join(F.transform(sketch, digits), ""))


def likeness(size_a: Column, a: Column, size_b: Column, b: Column) -> Column:
    """Exact Jaccard of two signature sets; two of no signatures are alike."""
    both = F.size(F.array_intersect(a, b))
    return F.when((size_a == 0) & (size_b == 0), F.lit(1.0)).otherwise(both / F.greatest(size_a + size_b - both, F.lit(1)))


def spot_links(documents: DataFrame, threshold: float = 0.8, anchors=tuple(ANCHORS), chain: int = CHAIN) -> tuple[DataFrame, DataFrame]:
    """(membership, links) of near-duplicate documents(doc_id, text).

    membership: doc_id, set_id for each row; documents of equal signature sets share a set_id. links: a, b, jaccard for every
    two different sets of at least `threshold`, a < b. A set of n signatures meets only sets that share one of its
    n - ceil(threshold * n) + 1 rarest, of lengths from threshold * n to n / threshold. Texts without words are in no link.
    """
    sets = _with_set(documents.select("doc_id", F.coalesce("text", F.lit("")).alias("_text")), "_text", "signatures", anchors, chain).select("doc_id", "signatures")
    membership = written(sets.select("doc_id", F.sha2(F.array_join("signatures", ","), 256).alias("set_id"), "signatures"), "spot-sets")
    distinct = membership.where(F.size("signatures") > 0).groupBy("set_id").agg(F.first("signatures").alias("signatures"))
    exploded = distinct.select("set_id", F.size("signatures").alias("n"), F.explode("signatures").alias("s"))
    often = exploded.groupBy("s").agg(F.count(F.lit(1)).alias("df"))
    ranked = exploded.join(often, "s").withColumn("rank", F.row_number().over(Window.partitionBy("set_id").orderBy("df", "s")))
    rare = ranked.where((F.col("rank") <= F.col("n") - F.ceil(F.lit(threshold) * F.col("n")) + 1) & (F.col("df") > 1)).select("set_id", "n", "s")
    # lengths fall into bands of ratio 1 / threshold: sets alike are in the same band or in neighbouring ones
    band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(1.0 / threshold))).cast("int")
    banded = rare.withColumn("band", band)
    left = banded.select(F.col("set_id").alias("a"), F.col("n").alias("na"), "s", F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    right = banded.select(F.col("set_id").alias("b"), F.col("n").alias("nb"), "s", "band")
    close = (F.col("a") < F.col("b")) & (F.least("na", "nb") >= F.lit(threshold) * F.greatest("na", "nb"))
    pairs = left.join(right, ["s", "band"]).where(close).select("a", "b").distinct()
    named = lambda k, s: distinct.select(F.col("set_id").alias(k), F.col("signatures").alias(s))
    both = pairs.join(named("a", "sa"), "a").join(named("b", "sb"), "b")
    shared = F.size(F.array_intersect("sa", "sb"))
    links = both.withColumn("jaccard", shared / (F.size("sa") + F.size("sb") - shared)).where(F.col("jaccard") >= threshold)
    return membership.select("doc_id", "set_id"), links.select("a", "b", "jaccard")


#: Documents of a range of ids, and most ranges.
RANGE, RANGES = 512, 1 << 20


def with_next(df: DataFrame, key: str, carried: list[str], rows_per_range: int = RANGE) -> DataFrame:
    """df with next_<column> for each carried column: that of the row that follows in descending key order, the first after the last.

    Ranges of keys are ordered each on its own. The row with the largest key of a range stands in for it at the end of
    the range before; these stand-ins are at most RANGES, so their ids may be broadcast. Null keys come last; ties are ordered
    by the first carried column.
    """
    low, high, n = df.agg(F.min(key), F.max(key), F.count(F.lit(1))).first()
    low, high = (low or 0), (high or 0)
    n_ranges = max(1, min(RANGES, n // rows_per_range))
    width = max(1, -(-(high - low + 1) // n_ranges))
    keyed = df.withColumn("_key", F.coalesce(F.col(key), F.lit(max(low - 1, -(1 << 63))).cast("long"))).withColumn("_range", F.expr(f"_key div {width}"))
    heads = keyed.select("_key", "_range").groupBy("_range").agg(F.max("_key").alias("_head"))
    up = Window.orderBy("_range")
    first, last = F.max("_head").over(Window.partitionBy()), F.min("_range").over(Window.partitionBy())
    heads = heads.select("_head", F.lead("_range").over(up).alias("_above"), (F.col("_head") == first).alias("_first"), last.alias("_last"))
    places = F.array_compact(
        F.array(
            F.struct(F.col("_range").alias("at"), F.lit(0).alias("turn")),
            F.when(F.col("_above").isNotNull(), F.struct(F.col("_above").alias("at"), F.lit(1).alias("turn"))),
            F.when(F.col("_first"), F.struct(F.col("_last").alias("at"), F.lit(2).alias("turn"))),
        )
    )
    placed = keyed.join(F.broadcast(heads), keyed["_key"] == heads["_head"], "left").withColumn("_place", F.explode(places))
    placed = placed.select(*df.columns, "_key", F.col("_place.at").alias("_at"), F.col("_place.turn").alias("_turn"))
    along = Window.partitionBy("_at").orderBy("_turn", F.col("_key").desc(), carried[0])
    after = {f"next_{column}": F.lead(column).over(along) for column in carried}  # one window, one shuffle
    return placed.withColumns(after).where("_turn = 0").drop("_key", "_at", "_turn")


def op6_spots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of all documents.

    Null texts count as empty. Rows that share a doc_id follow one another in the order of their texts; rows without a doc_id
    come last. An empty table gives no rows.
    """
    docs = common.table(spark, sf_dir, "documents", "doc_id", "text").withColumn("text", F.coalesce("text", F.lit("")))
    docs = with_next(with_sketch(docs, "text", "size", "sketch"), "doc_id", ["text", "size", "sketch"])
    docs = docs.withColumn("n_chars", F.length("text").cast("long"))
    half = F.floor(F.col("n_chars") / 2).cast("int")
    edited = F.concat(F.substring("text", 1, F.col("n_chars").cast("int") - half), F.substring("next_text", 1, half))
    docs = docs.withColumn("edited", edited).drop("text", "next_text")
    docs = with_sketch(docs, "edited", "edited_size", "edited_sketch")
    return docs.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        fingerprint_text(F.col("size"), F.col("sketch")).alias("fingerprint"),
        fingerprint_text(F.col("edited_size"), F.col("edited_sketch")).alias("edited_fingerprint"),
        likeness(F.col("size"), F.col("sketch"), F.col("edited_size"), F.col("edited_sketch")).alias("near_edited"),
        likeness(F.col("size"), F.col("sketch"), F.col("next_size"), F.col("next_sketch")).alias("near_next"),
    )
