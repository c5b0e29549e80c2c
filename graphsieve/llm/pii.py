"""Personal data by weak supervision, in DataFrame and SQL functions alone.

Candidates come from regular expressions. Labelers vote on each (+1, -1, or 0 for no opinion): its format, a gazetteer (domains, card
issuers, reserved networks, key words), the words around it, and what it is glued to. Expectation-maximisation over the counts of vote
patterns (a bounded table, whatever the input) estimates how reliable every labeler is for each kind. Its posteriors are the
labels from which a final span classifier (naive Bayes over features of the span) is trained by counting. Spans of the base
rules always stay; the method adds secrets, identity numbers and names that the classifier accepts.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsieve.llm.common import materialize

# The patterns of candidates. \G and the look-behinds keep searches linear; matches are the leftmost ones.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "secret": r"(?<![A-Za-z0-9_/+=-])[A-Za-z0-9_/+-]{24,}+",
    "id": r"(?<![0-9A-Za-z.,+-])[0-9]{9}+(?![0-9A-Za-z-]|[.,][0-9])",
    "name": r"(?<![A-Za-z])(?:Mr|Mrs|Ms|Dr|Prof|Herr|Frau|Monsieur|Madame|Señor|Señora)\.? \p{Lu}\p{L}+(?: \p{Lu}\p{L}+)?",
}
BASE = ("email", "ip", "card", "phone")
#: A text without such a character or word has no match; cheap to see.
NEEDS = {"email": "@", "phone": "+"}
# Gazetteers and key words, lower case.
DOMAINS = "com|org|net|edu|gov|io|de|fr|es|it|uk|eu|ch|at|info|biz"
CUES = {
    "email": "mail|contact|write|kontakt|courriel|correo", "ip": "ip|host|server|addr|login|from", "card": "card|visa|master|amex|credit|karte|carte|tarjeta|iban",
    "phone": "tel|phone|call|fax|mobil|fon|ruf", "secret": "token|secret|passw|api|key|auth|bearer|credential", "id": "ssn|id|passport|ausweis|nif|dni|tax|insurance|member|account",
    "name": "dear|sincerely|signed|hallo|cher|estimad|author|by",
}
COUNTER = "version|chapter|page|seite|figure|isbn|\\$|price|eur|usd"
LABELERS = ("format", "gazetteer", "context", "glue")
ACCEPT = 0.5
BEFORE, AFTER = 24, 8
#: Parts that the rows of a common shape are dealt to.
SALTS = 16


def _luhn(digits: Column) -> Column:
    """Whether a string of digits passes the Luhn test."""
    back = F.split(F.reverse(digits), "")
    terms = F.transform(back, lambda d, i: F.when(d == "", 0).when(i % 2 == 0, d.cast("int")).otherwise((d.cast("int") * 2) % 10 + F.floor(d.cast("int") / 5).cast("int")))
    return F.aggregate(terms, F.lit(0), lambda a, x: a + x) % 10 == 0


def _passes(kind: Column, match: Column) -> Column:
    """The base rules' further demands; other kinds have none."""
    octet = "0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
    digits = F.regexp_replace(match, "[^0-9]", "")
    n = F.length(digits)
    return (
        F.when(kind == "ip", match.rlike(rf"^{octet}(?:\.{octet}){{3}}$"))
        .when(kind == "card", F.when((n >= 13) & (n <= 19), _luhn(digits)).otherwise(False))
        .when(kind == "phone", (n >= 9) & (n <= 15))
        .otherwise(True)
    )


def candidates(docs: DataFrame) -> DataFrame:
    """One row per document, ``(uid, doc_id, found)``: per kind its matches and the lengths and edges of the text between them. Written once."""
    text = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    lists = []
    for kind, pattern in PATTERNS.items():
        has = F.col("text").contains(NEEDS[kind]) if kind in NEEDS else F.col("text").rlike("[0-9]") if kind in ("ip", "card", "id") else F.lit(True)
        matches = F.when(has, F.regexp_extract_all("text", F.lit(pattern), F.lit(0)))
        between = F.transform(F.split("text", pattern, -1), lambda p: F.struct(F.length(p).alias("n"), F.right(p, F.lit(BEFORE)).alias("end"), F.left(p, F.lit(AFTER)).alias("begin")))
        text = text.withColumn(f"m_{kind}", matches)
        lists.append(F.when(F.size(f"m_{kind}") > 0, F.struct(F.lit(kind).alias("kind"), F.col(f"m_{kind}").alias("matches"), between.alias("between"))))
    found = F.filter(F.array(*lists), lambda x: x.isNotNull())
    return materialize(text.select(F.monotonically_increasing_id().alias("uid"), "doc_id", found.alias("found")), "pii-found")


def _rows(found: DataFrame) -> DataFrame:
    """One row per candidate with its place (code points, end exclusive), the text around it, and whether it passes the base rules."""
    each = found.select("uid", F.explode("found").alias("f")).select("uid", "f.kind", F.posexplode(F.arrays_zip("f.between", "f.matches")).alias("i", "x"))
    order = Window.partitionBy("uid", "kind").orderBy("i")
    size = F.coalesce(F.length("x.matches"), F.lit(0))
    each = each.select("uid", "kind", F.col("x.matches").alias("match"), F.col("x.between.end").alias("before"), F.lead("x.between.begin").over(order).alias("after"), F.sum(F.col("x.between.n") + size).over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("end"))
    each = each.filter("match is not null")
    return each.withColumns({"start": F.col("end") - F.length("match"), "passes": _passes(F.col("kind"), F.col("match"))}).withColumn("base", F.col("kind").isin(*BASE) & F.col("passes"))


def _votes(rows: DataFrame) -> DataFrame:
    """The labelers' votes and the features of the span classifier."""
    kind, low = F.col("kind"), F.lower("match")
    digits = F.regexp_replace("match", "[^0-9]", "")
    mixed = F.col("match").rlike("[0-9]") & F.col("match").rlike("[A-Za-z]")
    shape = F.when(kind == "secret", F.when(mixed & (F.length(F.regexp_replace("match", "[^0-9]", "")) * 6 >= F.length("match")), 1).otherwise(-1)).when(kind == "id", F.when(F.substring("match", 1, 1) == "0", -1).otherwise(1)).when(kind == "name", 1)
    fmt = F.when(kind.isin(*BASE), F.when(F.col("passes"), 1).otherwise(-1)).otherwise(shape)
    gazetteer = (
        F.when(kind == "email", F.when(low.rlike(rf"\.(?:{DOMAINS})$"), 1).otherwise(-1))
        .when(kind == "ip", F.when(F.col("match").rlike(r"^(?:0|127|255)\."), -1).otherwise(0))
        .when(kind == "card", F.when(digits.rlike("^(?:3[47]|4|5[1-5]|2[2-7]|6)"), 1).otherwise(-1))
        .when(kind == "phone", F.when(F.col("match").rlike(r"^\+(?:1|3[0-9]|4[0-9]|[2-9][0-9])"), 1).otherwise(0))
        .when(kind == "secret", F.when(low.rlike("^(?:[0-9a-f]{32,}|sk-|ghp_|akia|xox)"), 1).otherwise(0))
        .otherwise(0)
    )
    around = F.lower("before")
    cue = reduce(lambda c, k: c.when(kind == k, around.rlike(CUES[k])), CUES, F.when(F.lit(False), F.lit(False)))
    context = F.when(cue, 1).when(around.rlike(f"(?:{COUNTER})\\W*$"), -1).otherwise(0)
    left, right = F.right("before", F.lit(1)), F.left("after", F.lit(1))
    glued = left.rlike(r"[\p{L}0-9._]") | right.rlike(r"[\p{L}0-9_]")
    glue = F.when(glued, -1).otherwise(F.when(left.rlike(r"^[\s\"'(<=:]?$"), 1).otherwise(0))
    marks = lambda c: F.when(c == "", "edge").when(c.rlike(r"\s"), "space").when(c.rlike(r"[\p{L}]"), "letter").when(c.rlike("[0-9]"), "digit").otherwise("mark")
    features = {
        "f_left": marks(left), "f_right": marks(F.coalesce(right, F.lit(""))), "f_size": F.least(F.length("match"), F.lit(64)).cast("string"),
        "f_shape": F.substring(F.regexp_replace(F.regexp_replace(F.regexp_replace("match", "[0-9]+", "9"), r"\p{Lu}+", "A"), r"\p{Ll}+", "a"), 1, 12), "f_cue": context.cast("string"),
    }
    return rows.withColumns({"format": fmt.cast("int"), "gazetteer": gazetteer.cast("int"), "context": context.cast("int"), "glue": glue.cast("int")} | features)


def estimate_reliability(patterns: list[tuple], rounds: int = 50) -> dict:
    """Expectation-maximisation over ``(votes..., count)``: the posterior of every vote pattern, the labelers' hit rates and the prior.

    Two classes; given the class, labelers vote independently. Counts are smoothed by one half; starts from the mean vote.
    """
    votes = [tuple(p[:-1]) for p in patterns]
    n = [p[-1] for p in patterns]
    post = [1 / (1 + math.exp(-1.5 * sum(v))) for v in votes]
    rates: list = []
    prior = 0.5
    for _ in range(rounds if votes else 0):
        total = sum(n)
        prior = min(0.99, max(0.01, (sum(p * k for p, k in zip(post, n)) + 0.5) / (total + 1)))
        rates = []
        for j in range(len(votes[0])):
            by = {(c, x): 0.5 for c in (0, 1) for x in (-1, 0, 1)}
            by[1, 1] += 1.0  # a labeler is better than chance until counts say otherwise
            by[0, -1] += 1.0
            for v, p, k in zip(votes, post, n):
                by[1, v[j]] += p * k
                by[0, v[j]] += (1 - p) * k
            rates.append({(c, x): y / sum(by[c, z] for z in (-1, 0, 1)) for (c, x), y in by.items()})
        log = [math.log(prior / (1 - prior)) + sum(math.log(r[1, x] / r[0, x]) for r, x in zip(rates, v)) for v in votes]
        post = [1 / (1 + math.exp(-max(-30.0, min(30.0, x)))) for x in log]
    return {"posterior": dict(zip(votes, post)), "rates": dict(zip(LABELERS, rates)), "prior": prior}


def _table(column: Column, values: dict, default: float) -> Column:
    """A column looked up in a small table of literals."""
    if not values:
        return F.lit(default)
    pairs = F.create_map(*[x for k, v in sorted(values.items()) for x in (F.lit(k), F.lit(float(v)))])
    return F.coalesce(F.try_element_at(pairs, column), F.lit(default))


def classify(rows: DataFrame) -> tuple[DataFrame, dict]:
    """Candidates with ``probability``: votes, reliabilities by kind, and the classifier trained on their posteriors."""
    voted = materialize(_votes(rows), "pii-votes")
    by_kind: dict[str, list] = {}
    for r in voted.groupBy("kind", *LABELERS).count().collect():  # at most 7 * 3**4 rows
        by_kind.setdefault(r[0], []).append(tuple(r)[1:])
    models = {k: estimate_reliability(sorted(p)) for k, p in by_kind.items()}
    code = F.concat_ws(":", "kind", *LABELERS)
    posterior = {":".join(map(str, (k, *v))): p for k, m in models.items() for v, p in m["posterior"].items()}
    voted = voted.withColumn("soft", _table(code, posterior, 0.5))
    score = _table(F.col("kind"), {k: math.log(m["prior"] / (1 - m["prior"])) for k, m in models.items()}, 0.0)
    sums = [F.sum("soft").alias("yes"), F.sum(1 - F.col("soft")).alias("no")]
    totals = {r.kind: (r.yes, r.no) for r in voted.groupBy("kind").agg(*sums).collect()}
    for f in ("f_left", "f_right", "f_size", "f_cue"):
        counts = voted.groupBy("kind", f).agg(*sums).collect()  # at most 7 * 64 rows
        weights = {f"{r[0]}:{r[1]}": math.log((r.yes + 0.5) / (totals[r[0]][0] + 1)) - math.log((r.no + 0.5) / (totals[r[0]][1] + 1)) for r in counts}
        score = score + _table(F.concat_ws(":", "kind", f), weights, 0.0)
    # shapes have no bound: their weights are a table, joined with salt, as a few shapes are very common
    whole = _table(F.col("kind"), {k: math.log(no + 1) - math.log(yes + 1) for k, (yes, no) in totals.items()}, 0.0)
    shapes = voted.groupBy("kind", "f_shape").agg(*sums).select("kind", "f_shape", (F.log(F.col("yes") + 0.5) - F.log(F.col("no") + 0.5) + whole).alias("w_shape"))
    shapes = materialize(shapes, "pii-shapes").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    voted = voted.withColumn("salt", F.pmod(F.xxhash64("uid", "start"), F.lit(SALTS)).cast("int")).join(shapes, ["kind", "f_shape", "salt"], "left").drop("salt")
    score = score + F.coalesce("w_shape", F.lit(0.0))
    logit = F.greatest(F.lit(-30.0), F.least(F.lit(30.0), score))
    return voted.withColumn("probability", 1 / (1 + F.exp(-logit))), models


def find_spans(found: DataFrame, accept: float = ACCEPT) -> DataFrame:
    """Rows ``(uid, kind, start, end, base, probability)``: base spans, and accepted others that touch no base span and no earlier other."""
    rows = _rows(found)
    scored, _ = classify(rows)
    kept = scored.filter(F.col("base") | (~F.col("kind").isin(*BASE) & (F.col("probability") >= accept)))
    order = Window.partitionBy("uid").orderBy("start", F.desc("base"), "end", "kind")
    base_end = F.max(F.when(F.col("base"), F.col("end"))).over(order.rowsBetween(Window.unboundedPreceding, -1))
    base_start = F.min(F.when(F.col("base"), F.col("start"))).over(order.rowsBetween(1, Window.unboundedFollowing))
    any_end = F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1))
    kept = kept.select("uid", "kind", "start", "end", "base", "probability", base_end.alias("be"), base_start.alias("bs"), any_end.alias("ae"))
    clear = (F.coalesce("be", F.lit(0)) <= F.col("start")) & (F.coalesce("ae", F.lit(0)) <= F.col("start")) & (F.col("bs").isNull() | (F.col("bs") >= F.col("end")))
    return kept.filter(F.col("base") | clear).drop("be", "bs", "ae")


_RANK = {k: i for i, k in enumerate((*BASE, "secret", "id", "name"))}


def _joined(spans: Column) -> Column:
    """kind:start:end, by kind as listed, then start."""
    names = F.array(*[F.lit(k) for k in _RANK])
    return F.array_join(F.transform(F.array_sort(spans), lambda s: F.concat_ws(":", F.element_at(names, s["rank"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def _by_document(spans: DataFrame) -> DataFrame:
    rank = reduce(lambda c, k: c.when(F.col("kind") == k, _RANK[k]), _RANK, F.when(F.lit(False), -1))
    item = F.struct(rank.alias("rank"), F.col("start"), F.col("end"))
    count = lambda k: F.sum(F.when(F.col("base") & (F.col("kind") == k), 1).otherwise(0)).alias(f"n_{k}")
    return spans.groupBy("uid").agg(*[count(k) for k in BASE], F.collect_list(F.when(F.col("base"), item)).alias("base_spans"), F.collect_list(item).alias("all_spans"))


def pii_report(docs: DataFrame) -> DataFrame:
    """One row per document: base counts and digest, and all spans. Null texts are empty; a document without spans has empty strings' digests."""
    found = candidates(docs)
    spans = _by_document(find_spans(found))
    out = found.select("uid", "doc_id").join(spans, "uid", "left")
    empty = F.lit("")
    return out.select(
        "doc_id", *[F.coalesce(f"n_{k}", F.lit(0)).cast("long").alias(f"n_{k}") for k in BASE],
        F.sha2(F.coalesce(_joined(F.col("base_spans")), empty).cast("binary"), 256).alias("base_sha256"), F.coalesce(_joined(F.col("all_spans")), empty).alias("spans"),
    )


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with every span replaced by its kind in angle brackets, n_chars (where it is a column) made to fit. Spans that meet are one."""
    docs = materialize(docs.withColumn("_row", F.monotonically_increasing_id()), "pii-docs")
    found = candidates(docs.select(F.col("_row").alias("doc_id"), "text"))
    spans = find_spans(found).join(found.select("uid", F.col("doc_id").alias("_row")), "uid")
    order = Window.partitionBy("_row").orderBy("start", "end", "kind")
    spans = spans.withColumn("reach", F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1)))
    spans = spans.withColumn("begins", (F.coalesce("reach", F.lit(-1)) < F.col("start")).cast("int")).withColumn("run", F.sum("begins").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    runs = spans.groupBy("_row", "run").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.array_join(F.sort_array(F.collect_set("kind")), "+").alias("kind"))
    prior = F.lag("end", 1, 0).over(Window.partitionBy("_row").orderBy("start"))
    cuts = runs.withColumn("from", prior).groupBy("_row").agg(F.sort_array(F.collect_list(F.struct("start", "from", "end", "kind"))).alias("cuts"), F.max("end").alias("last"))
    joined = docs.join(cuts, "_row", "left")
    piece = lambda c: F.concat(F.substring(F.col("text"), (c["from"] + 1).cast("int"), (c["start"] - c["from"]).cast("int")), F.lit("<"), F.upper(c["kind"]), F.lit(">"))
    text = F.when(F.col("cuts").isNull(), F.col("text")).otherwise(F.concat(F.array_join(F.transform("cuts", piece), ""), F.expr("substring(text, cast(last + 1 as int))")))
    out = joined.withColumn("text", text)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*[c for c in docs.columns if c != "_row"])
