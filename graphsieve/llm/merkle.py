"""Document fingerprints: a Merkle tree over paragraphs and sections, in SQL functions alone.

Sections are parted by blank lines, paragraphs by line ends; a paragraph's leaves are its sentences, cut after 64 characters.
A leaf's hash is the md5 of its text, an inner node's the md5 of its children's hashes, the root's a sha256: equal roots mean equal
texts as far as these hashes go. The fingerprint is ``root~section;section``, a section ``paragraph,paragraph``, a paragraph the starts of its
leaves' hashes (8 digits each), by which branches that differ name the sections and paragraphs that were edited.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Fixed value: a leaf is a sentence (ended by . ! or ?) of up to 64 characters, or 64 characters.
LEAF = r"[^\n]{1,63}?[.!?](?= |$)|[^\n]{1,64}"

#: Ranges of doc_id: their rows and most number, and how many bounds are looked at together.
RANGE_ROWS, MAX_RANGES, STRIDE = 512, 1 << 14, 128


def tree(text: Column) -> Column:
    """Leaves' hashes of a text: sections of paragraphs, as nested lists joined by ``;`` and ``,``."""
    leaves = lambda p: F.array_join(F.transform(F.regexp_extract_all(p, F.lit(LEAF), F.lit(0)), lambda x: F.md5(x.cast("binary"))), "")
    section = lambda s: F.array_join(F.transform(F.split(s, "\n"), leaves), ",")
    return F.array_join(F.transform(F.split(text, "\n\n"), section), ";")


def root(leaves: Column) -> Column:
    """Root hash over the sections' hashes, each over its paragraphs' hashes."""
    paragraph = lambda p: F.md5(p.cast("binary"))
    section = lambda s: F.md5(F.array_join(F.transform(F.split(s, ","), paragraph), "").cast("binary"))
    return F.substring(F.sha2(F.array_join(F.transform(F.split(leaves, ";"), section), "").cast("binary"), 256), 1, 32)


def fingerprint(leaves: Column) -> Column:
    return F.concat_ws("~", root(leaves), F.regexp_replace(leaves, "([0-9a-f]{8})[0-9a-f]{24}", "$1"))


def leaf_set(print_: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.substring_index(print_, "~", -1), F.lit("[0-9a-f]{8}"), F.lit(0)))


def likeness(a: Column, b: Column) -> Column:
    """Share of leaves in common (twice the common ones over both counts); 1 for equal roots, also of empty texts."""
    x, y = leaf_set(a), leaf_set(b)
    same = F.substring_index(a, "~", 1) == F.substring_index(b, "~", 1)
    return F.when(same, 1.0).otherwise(2.0 * F.size(F.array_intersect(x, y)) / F.greatest(F.size(x) + F.size(y), F.lit(1)))


def fingerprints(docs: DataFrame) -> DataFrame:
    """``docs`` with a ``fingerprint`` column; null texts count as empty. A column of that name is replaced."""
    kept = [c for c in docs.columns if c != "fingerprint"]
    return docs.select(*kept, tree(F.coalesce("text", F.lit(""))).alias("_leaves")).select(*kept, fingerprint(F.col("_leaves")).alias("fingerprint"))


def edited_branches(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Places of the paragraphs that differ between two fingerprints of a row: ``pairs`` with (section, paragraph), both from 0.

    Subtrees with equal hashes are not entered. Rows with equal roots give none.
    """
    differ = pairs.filter(F.substring_index(F.col(a), "~", 1) != F.substring_index(F.col(b), "~", 1))
    parts = lambda c, sep: F.split(c, sep)
    s = differ.withColumn("_s", F.arrays_zip(parts(F.substring_index(F.col(a), "~", -1), ";").alias("x"), parts(F.substring_index(F.col(b), "~", -1), ";").alias("y")))
    s = s.select(*pairs.columns, F.posexplode("_s").alias("section", "_s")).filter(~F.col("_s.x").eqNullSafe(F.col("_s.y")))
    p = s.withColumn("_p", F.arrays_zip(parts(F.coalesce("_s.x", F.lit("")), ",").alias("x"), parts(F.coalesce("_s.y", F.lit("")), ",").alias("y")))
    return p.select(*pairs.columns, "section", F.posexplode("_p").alias("paragraph", "_p")).filter(~F.col("_p.x").eqNullSafe(F.col("_p.y"))).drop("_p")


def _ranges(docs: DataFrame) -> tuple[Column, DataFrame]:
    """Ranges of doc_id of about equal counts: a column that numbers them, and what doc_id starts the one behind each.

    Bounds are quantiles of the ids, so one far-off id moves none of the others together; the driver sees a bound and a head per range. Null ids are
    in the first. A row finds its range among every STRIDE-th bound and then among those behind it.
    """
    spark = docs.sparkSession
    ids = docs.select("doc_id")
    total = ids.count()
    ranges = max(1, min(MAX_RANGES, -(-total // RANGE_ROWS)))
    found = ids.agg(F.percentile_approx("doc_id", [k / ranges for k in range(1, ranges)], max(10_000, 8 * ranges))).first()[0] if ranges > 1 else []
    bounds = sorted(set(found or []))
    listed = lambda x: F.expr(f"cast(split('{','.join(map(str, x))}', ',') as array<bigint>)") if x else F.array().cast("array<bigint>")
    under = lambda a: F.size(F.filter(a, lambda b: b <= F.col("doc_id")))
    # the coarse number says how many whole strides of bounds lie at or below the id
    coarse = under(listed(bounds[STRIDE - 1 :: STRIDE])) * STRIDE
    part = F.when(F.col("doc_id").isNull(), F.lit(0)).otherwise(coarse + under(F.slice(listed(bounds), coarse + 1, F.lit(STRIDE))))
    heads = sorted(tuple(r) for r in ids.groupBy(part.alias("part")).agg(F.min("doc_id"), F.max(F.col("doc_id").isNull())).collect())
    heads = [(p, None if null else d) for p, d, null in heads]
    behind = [(d, heads[k - 1][0]) for k, (_, d) in enumerate(heads)]
    return part, spark.createDataFrame(behind, "head long, to int")


def edit_report(docs: DataFrame) -> DataFrame:
    """Fingerprints of whole texts and of their edited texts, and likenesses to the edited text and to the next document.

    The edited text: the last half (rounded down) of the characters gives way to as many of the next document's first, or all it has.
    Next is by ascending doc_id (equal ids: by a hash of the text; null ids first), after the last comes the first. Null texts are empty.
    Documents are dealt to ranges of ids once; the documents that start a range are also lent to the range before.
    """
    part, behind = _ranges(docs)
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).select("doc_id", "text", tree(F.col("text")).alias("leaves"))
    rows = rows.select("doc_id", "text", fingerprint(F.col("leaves")).alias("fp"), part.alias("part")).join(F.broadcast(behind), F.col("doc_id").eqNullSafe(F.col("head")), "left")
    own, lent = F.struct(F.col("part").alias("at"), F.lit(False).alias("lent")), F.struct(F.col("to").alias("at"), F.lit(True).alias("lent"))
    rows = rows.select("doc_id", "text", "fp", F.explode(F.when(F.col("to").isNull(), F.array(own)).otherwise(F.array(own, lent))).alias("x")).select("doc_id", "text", "fp", "x.*")
    order = Window.partitionBy("at").orderBy("lent", "doc_id", F.xxhash64("text"))
    both = rows.select("*", F.lead("text").over(order).alias("next"), F.lead("fp").over(order).alias("next_fp")).filter(~F.col("lent"))
    both = both.withColumn("n", F.length("text")).withColumn("half", F.expr("cast(n div 2 as int)"))
    both = both.select("doc_id", "n", "fp", "next_fp", F.concat(F.expr("substring(text, 1, n - half)"), F.expr("substring(next, 1, half)")).alias("edited"))
    both = both.select("doc_id", "n", "fp", "next_fp", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), tree(F.col("edited")).alias("edited_leaves"))
    both = both.select("doc_id", "n", "fp", "next_fp", "edited_sha256", fingerprint(F.col("edited_leaves")).alias("edited_fp"))
    return both.select(
        "doc_id", F.col("n").cast("long").alias("n_chars"), "edited_sha256", F.col("fp").alias("fingerprint"), F.col("edited_fp").alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("edited_fp")).cast("double").alias("near_edited"), likeness(F.col("fp"), F.col("next_fp")).cast("double").alias("near_next"),
    )
