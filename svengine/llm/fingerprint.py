"""Merkle fingerprints of documents, with DataFrame functions only.

A text is cut at newlines into paragraphs and paragraphs into leaves of LEAST to MOST code points; runs of paragraphs are the sections, and the root
covers the sections. All cuts follow from the content: a leaf ends where a character of one fixed class meets one of another, a section after a
paragraph whose hash begins with 0 or 1 (or after RUN paragraphs). So an insertion changes the branches it is in, and cuts fall into step again
right after it, in texts of every length. Where no pair of characters marks a cut, leaves are MOST code points.

Every code point belongs to one leaf, so two texts have the same root if and only if they are equal (up to SHA-256 collisions).
Likeness and edits come from descending through unequal branches only. Null counts as the empty text, whose tree has no leaves.
A row without a doc_id has no place in the order of documents, so fingerprints() gives it no row; rows that repeat a doc_id follow one another by
their texts. Columns other than doc_id and text are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

LEAST, MOST, RUN = 4, 24, 32
#: Hex digits kept of a leaf's hash, and of other nodes' hashes in the printed form.
SHORT = 8


def _class(rest: int) -> str:
    """Regex class of the characters that leave `rest` mod 8, above Latin-1 by 16 code points at once."""
    one = "".join(f"\\x{c:02x}" for c in range(256) if c % 8 == rest and c != 10)
    wide = "".join(f"\\u{c:04x}-\\u{c + 15:04x}" for c in range(0x100, 0xD800, 16) if (c >> 4) % 8 == rest)
    return f"(?:[{one}]|(?![\\x00-\\xff])[{wide}])"


PARAGRAPH = r"[^\n]*\n|[^\n]+"
LEAF = rf"[^\n]{{{LEAST - 1},{MOST - 1}}}?{_class(0)}(?={_class(1)}|{_class(5)})|[^\n]{{1,{MOST}}}\n?|\n"
#: On paragraphs' nodes, each a hash, a colon and its leaves with commas between; nodes have slashes between.
SECTION = rf"((?:[2-9a-f][^/]*/){{0,{RUN - 1}}}[^/]+)/?"


def leaves(text: Column) -> Column:
    """Array of leaves whose concatenation is the text."""
    return F.flatten(F.transform(F.regexp_extract_all(text, F.lit(PARAGRAPH), F.lit(0)), lambda p: F.regexp_extract_all(p, F.lit(LEAF), F.lit(0))))


def with_tree(df: DataFrame, text: str, to: str) -> DataFrame:
    """df with the struct column `to`: root (64 hex digits) and sections, each its paragraphs' nodes in one string."""
    paragraphs = F.regexp_extract_all(F.coalesce(F.col(text), F.lit("")), F.lit(PARAGRAPH), F.lit(0))
    full = F.transform(paragraphs, lambda p: F.transform(F.regexp_extract_all(p, F.lit(LEAF), F.lit(0)), lambda x: F.sha2(x, 256)))
    nodes = F.transform(full, lambda f: F.concat(F.sha2(F.array_join(f, ""), 256), F.lit(":"), F.array_join(F.transform(f, lambda x: F.substring(x, 1, SHORT)), ",")))
    out = df.withColumn(f"_{to}", F.regexp_extract_all(F.array_join(nodes, "/"), F.lit(SECTION), F.lit(1)))
    root = F.sha2(F.array_join(F.transform(F.col(f"_{to}"), lambda s: F.sha2(s, 256)), ""), 256)
    return out.withColumn(to, F.struct(root.alias("root"), F.col(f"_{to}").alias("sections"))).drop(f"_{to}")


def printed(tree: str) -> Column:
    """The fingerprint as one string: the root, then for each section its hash and its paragraphs, each with its hash and its leaves'."""
    sections = F.array_join(F.transform(F.col(f"{tree}.sections"), lambda s: F.concat(F.substring(F.sha2(s, 256), 1, SHORT), F.lit("="), s)), "/")
    return F.concat(F.col(f"{tree}.root"), F.lit(":"), F.translate(F.regexp_replace(sections, rf"(?<![^=/])([0-9a-f]{{{SHORT}}})[0-9a-f]{{{64 - SHORT}}}:", "$1:"), ",", ""))


def _paragraphs(sections: Column) -> Column:
    return F.array_remove(F.split(F.array_join(sections, "/"), "/"), "")


def _leaves(paragraphs: Column) -> Column:
    return F.array_remove(F.split(F.array_join(F.transform(paragraphs, lambda p: F.substring(p, 66, 1 << 30)), ","), ","), "")


def with_likeness(df: DataFrame, a: str, b: str, to: str) -> DataFrame:
    """df with `to`: 1 for equal roots; else the leaves that both trees have, over the leaves of the one that has more.

    Leaves below equal sections and paragraphs count without being compared; below unequal ones distinct leaves are.
    """
    # each step is a column of its own, so that it is computed once
    s, t, x, y = F.col(f"{a}.sections"), F.col(f"{b}.sections"), F.col("_x"), F.col("_y")
    out = df.withColumns({"_same": F.size(_leaves(_paragraphs(F.array_intersect(s, t)))), "_x": _paragraphs(F.array_except(s, t)), "_y": _paragraphs(F.array_except(t, s))})
    out = out.withColumns({"_same": F.col("_same") + F.size(_leaves(F.array_intersect(x, y))), "_x": F.array_distinct(_leaves(F.array_except(x, y))), "_y": F.array_distinct(_leaves(F.array_except(y, x)))})
    part = (F.col("_same") + F.size(F.array_intersect(x, y))) / F.greatest(F.col("_same") + F.greatest(F.size(x), F.size(y)), F.lit(1))
    return out.withColumn(to, F.when(F.col(f"{a}.root") == F.col(f"{b}.root"), F.lit(1.0)).otherwise(part)).drop("_same", "_x", "_y")


def changed_paragraphs(a: str, b: str) -> Column:
    """Numbers (from 0) of a's paragraphs that b doesn't have, found below sections of a that b doesn't have."""
    s, t = F.col(f"{a}.sections"), F.col(f"{b}.sections")
    gone = F.array_except(_paragraphs(F.array_except(s, t)), _paragraphs(F.array_except(t, s)))
    return F.filter(F.transform(_paragraphs(s), lambda p, i: F.when(F.array_contains(gone, p), i)), lambda i: i.isNotNull())


#: Bytes of text that one range of doc_ids holds on average, at most.
RANGE_BYTES = 8_000_000


def fingerprints(docs: DataFrame) -> DataFrame:
    """Per document: fingerprint, that of its edited text, and the likeness to the edited text's and to the next document's.

    The next document is the next one by doc_id; the last one's is the first. Texts are shuffled once, into ranges of doc_ids. The next
    of a range's last document is the first of the next range that has any; these few are taken from the same shuffle.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text")).where("doc_id is not null")
    size = rows.agg(F.sum(F.octet_length("text") + 1)).first()[0] or 0
    most = max(1, min(RANGE_BYTES, size // (4 * int(spark.conf.get("spark.sql.shuffle.partitions")))))
    dealt = common.in_ranges(rows, "doc_id", F.octet_length("text") + 1, most)
    narrow = dealt.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    hop = narrow.select("part", F.coalesce(F.lag("part").over(Window.orderBy("part")), F.max("part").over(Window.partitionBy())).alias("before"))  # a row of two numbers for each range
    order = Window.partitionBy("part").orderBy("doc_id", "text")
    ordered = dealt.withColumns({"next_text": F.lead("text").over(order), "place": F.row_number().over(order)})
    first = ordered.where("place = 1").join(hop, "part").select(F.col("before").alias("part"), F.col("text").alias("first_text"))
    last = with_tree(with_tree(ordered.where("next_text is null").drop("next_text").join(first, "part").withColumnRenamed("first_text", "next_text"), "text", "tree"), "next_text", "next_tree")
    inner = with_tree(ordered, "text", "tree").withColumn("next_tree", F.lead("tree").over(order)).where("next_text is not null")
    f = inner.unionByName(last)
    f = f.withColumn("n_chars", F.char_length("text").cast("long")).withColumn("_k", F.floor(F.col("n_chars") / 4).cast("int"))
    f = f.withColumn("edited", F.concat(F.expr("substring(text, 1, int(n_chars) - _k)"), F.expr("substring(next_text, 1, _k)")))
    f = with_likeness(with_likeness(with_tree(f, "edited", "edited_tree"), "tree", "edited_tree", "near_edited"), "tree", "next_tree", "near_next")
    return f.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), printed("tree").alias("fingerprint"), printed("edited_tree").alias("edited_fingerprint"),
        "near_edited", "near_next",
    )


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(common.table(spark, sf_dir, "documents"))
