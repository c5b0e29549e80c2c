"""Labelled graphs on the given tables, and the same graphs told in SQL for the oracle.

Vertex ids are ``kind * 2**40 + key``. Keys are the tables' own integers; strings and pairs of numbers get their place in the sorted list
of distinct values (``dictionary``), so no two of them share an id. Sources are DataFrame code; the oracle's SQL is written apart from them.
"""

from __future__ import annotations

import string
from collections.abc import Callable
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphsieve.functions.storage import discard, materialize
from graphsieve.operators.reduce import LabeledGraph, labelled_edges, symmetric
from graphsieve.plans.template import Template

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
KINDS = {k: i + 1 for i, k in enumerate("region nation customer supplier part order event user page link conversation turn doc source vec lattice rmat host item".split())}
# Second-level domains that stand for a label rather than the country's domain behind them.
SECOND_LEVEL = ("ac", "co", "com", "edu", "gov", "net", "or", "org")
HREF = 'href="([^"]*)"'
LATTICE_WIDTH = 50


# ---- Spark side -----------------------------------------------------------------------------------------------------------------


def key(kind: str, column: Column | str) -> Column:
    return (F.lit(KINDS[kind] << 40) + (F.col(column) if isinstance(column, str) else column).cast("long")).cast("long")


def dictionary(values: DataFrame) -> DataFrame:
    """Distinct rows with ``place``: their number in sorted order, from 0. Rows are dealt by range, numbered within a range, and moved on by the
    lengths of the ranges before (one row per partition); no task sees all of them. Rows with nulls go."""
    cols = values.columns
    d = values.dropna().distinct().repartitionByRange(*cols).sortWithinPartitions(*cols)
    d = materialize(d.withColumn("_part", F.spark_partition_id()).withColumn("_pos", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))), "dictionary")
    before = F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))  # a row per partition
    offsets = d.groupBy("_part").agg(F.count("*").alias("_n")).select("_part", F.coalesce(before, F.lit(0)).alias("_before"))
    return d.join(F.broadcast(offsets), "_part").select(*cols, (F.col("_before") + F.col("_pos")).cast("long").alias("place"))


def domain_label(url: str | Column, second: tuple[str, ...] = SECOND_LEVEL) -> Column:
    """The label of a web page: its second-level domain if that is one of ``second``, else the top-level one; null without a host."""
    host = F.regexp_extract(url if isinstance(url, Column) else F.col(url), "^[a-z]+://([^/:?#]+)", 1)
    parts = F.split(F.lower(host), "[.]")
    below = F.try_element_at(parts, F.lit(-2))
    return F.when(host == "", F.lit(None)).otherwise(F.concat(F.lit("."), F.when((F.size(parts) > 2) & below.isin(*second), below).otherwise(F.element_at(parts, -1))))


def _union(*parts: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _v(df: DataFrame, vid: Column, label: Column | str) -> DataFrame:
    return df.select(vid.alias("vid"), (F.lit(label) if isinstance(label, str) else label).alias("label"))


def _e(df: DataFrame, a: Column, b: Column) -> DataFrame:
    return df.select(a.alias("a"), b.alias("b"))


def _trade_parts(t: Callable[[str], DataFrame]):
    """Vertices by kind; and edges by the kinds of their ends, with the kind whose labels are joined first: that of which a template wants the smaller share."""
    lines = t("lineitem")
    v = {
        "region": _v(t("region"), key("region", "r_regionkey"), "region"), "nation": _v(t("nation"), key("nation", "n_nationkey"), "nation"),
        "customer": _v(t("customer"), key("customer", "c_custkey"), F.concat(F.lit("cust:"), "c_mktsegment")), "supplier": _v(t("supplier"), key("supplier", "s_suppkey"), "supplier"),
        "part": _v(t("part"), key("part", "p_partkey"), F.concat(F.lit("part:"), "p_type")), "order": _v(t("orders"), key("order", "o_orderkey"), F.concat(F.lit("order:"), "o_orderstatus")),
    }
    order, part, supplier = key("order", "l_orderkey"), key("part", "l_partkey"), key("supplier", "l_suppkey")
    e = [
        (("nation", "region"), "nation", _e(t("nation"), key("nation", "n_nationkey"), key("region", "n_regionkey"))), (("customer", "nation"), "customer", _e(t("customer"), key("customer", "c_custkey"), key("nation", "c_nationkey"))),
        (("supplier", "nation"), "supplier", _e(t("supplier"), key("supplier", "s_suppkey"), key("nation", "s_nationkey"))), (("order", "customer"), "customer", _e(t("orders"), key("order", "o_orderkey"), key("customer", "o_custkey"))),
        (("order", "part"), "part", _e(lines, order, part)), (("order", "supplier"), "order", _e(lines, order, supplier)), (("part", "supplier"), "part", _e(lines, part, supplier)),
    ]
    return v, e


def _trade(t: Callable[[str], DataFrame]):
    v, e = _trade_parts(t)
    return _union(*v.values()), _union(*[pairs for _, _, pairs in e])


def coded(v: DataFrame, t: Template | None) -> DataFrame:
    """Vertices with their labels; with a template, those of its labels, with the label's place among them: joins and a distinct carry a number."""
    if t is None:
        return v
    code = reduce(lambda c, x: c.when(F.col("label") == x[1], F.lit(x[0]).cast("byte")), enumerate(t.by_label), F)
    return v.filter(F.col("label").isin(list(t.by_label))).select("vid", code.alias("label"))


def distinct_pairs(e: DataFrame, t: Template | None) -> DataFrame:
    """Distinct ``(a, b, alabel, blabel)`` of pairs with labels as ``coded`` has them: with a template, those that one of its edges may be."""
    told = ("a", "b", "alabel", "blabel")
    if t is None:
        return e.select(*told).distinct()
    names = list(t.by_label)
    wanted = {(names.index(t.labels[x]), names.index(t.labels[y])) for a, b in t.edges for x, y in ((a, b), (b, a))}
    e = e.filter(reduce(Column.__or__, [(F.col("alabel") == x) & (F.col("blabel") == y) for x, y in sorted(wanted)], F.lit(False))).select(*told).distinct()
    name = lambda c: reduce(lambda w, x: w.when(F.col(c) == x[0], F.lit(x[1])), enumerate(names), F).alias(c)
    return e.select("a", "b", name("alabel"), name("blabel"))


def labelled_pairs(pairs: DataFrame, va: DataFrame, vb: DataFrame, t: Template | None) -> DataFrame:
    """Distinct ``(a, b, alabel, blabel)`` of pairs whose ends lie among ``va`` and ``vb``: with a template, those that one of its edges may be.

    ``va`` is joined first. The last join deals by one end, so that the distinct needs no shuffle of its own.
    """
    e = pairs.filter("a <> b")
    for v, end in ((va, "a"), (vb, "b")):
        e = e.join(coded(v, t).select(F.col("vid").alias(end), F.col("label").alias(f"{end}label")).hint("shuffle_hash"), end, "left" if t is None else "inner")
    return distinct_pairs(e, t)


def _trade_labelled(tables, t: Template | None) -> DataFrame:
    """Edges of the trade graph with their ends' labels, each once: an edge kind is labelled by itself, so that no join or distinct sees all kinds both ways."""
    v, e = _trade_parts(tables)
    return _union(*[labelled_pairs(pairs, v[a], v[b], t) if first == a else labelled_pairs(_e(pairs, F.col("b"), F.col("a")), v[b], v[a], t) for (a, b), first, pairs in e])


def _trade_fine(t):
    """The trade graph with rarer labels: rich customers, and parts by brand."""
    v, e = _trade(t)
    rich = t("customer").filter("c_acctbal > 9000").select(key("customer", "c_custkey").alias("vid"), F.lit("rich").alias("own"))
    brand = t("part").select(key("part", "p_partkey").alias("vid"), F.concat(F.lit("brand:"), "p_brand").alias("own"))
    return v.join(rich.unionByName(brand), "vid", "left").select("vid", F.coalesce("own", "label").alias("label")), e


def _shipped(t):
    """Directed edges with labels: an order ships parts (by return flag) and suppliers' goods (by line status)."""
    v, _ = _trade(t)
    lines = t("lineitem")
    e = _union(
        lines.select(key("order", "l_orderkey").alias("a"), key("part", "l_partkey").alias("b"), F.col("l_returnflag").alias("elabel")),
        lines.select(key("order", "l_orderkey").alias("a"), key("supplier", "l_suppkey").alias("b"), F.col("l_linestatus").alias("elabel")),
        lines.select(key("part", "l_partkey").alias("a"), key("supplier", "l_suppkey").alias("b"), F.lit("from").alias("elabel")),
    )
    return v, e


def _session(t):
    events = t("events")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    following = events.select("event_id", F.lead("event_id").over(order).alias("next")).filter("next is not null")
    v = _union(_v(events, key("event", "event_id"), F.col("event_type")), _v(events.select("user_id").distinct(), key("user", "user_id"), "user"))
    return v, _union(_e(events, key("event", "event_id"), key("user", "user_id")), _e(following, key("event", "event_id"), key("event", "next")))


def _conv(t):
    turns = t("conversations").select("conv_id", "turn", "role")
    known = turns.join(dictionary(turns.select("conv_id", "turn")), ["conv_id", "turn"])
    one = known.select("conv_id", "turn", "place")
    after = one.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("place").alias("next"))
    v = _union(_v(turns.select("conv_id").distinct(), key("conversation", "conv_id"), "conv"), _v(known, key("turn", "place"), F.col("role")))
    return v, _union(_e(one, key("turn", "place"), key("conversation", "conv_id")), _e(one.join(after, ["conv_id", "turn"]), key("turn", "place"), key("turn", "next")))


def _coorder(label: Callable[[], Column]):
    def told(t):
        own = t("lineitem").select("l_orderkey", "l_partkey").distinct()
        other = own.select("l_orderkey", F.col("l_partkey").alias("other"))
        pairs = own.join(other, "l_orderkey").filter("l_partkey < other").select("l_partkey", "other").distinct()
        return _v(t("part"), key("part", "p_partkey"), label()), _e(pairs, key("part", "l_partkey"), key("part", "other"))

    return told


def _coorder_labelled(label: Callable[[], Column]):
    """Parts of one order with their labels, each pair once: labels are joined to the lines, which are fewer than the pairs."""

    def told(tables, t: Template | None) -> DataFrame:
        labels = coded(_v(tables("part"), key("part", "p_partkey"), label()), t)
        lines = tables("lineitem").filter("l_orderkey is not null and l_partkey is not null").select("l_orderkey", key("part", "l_partkey").alias("vid"))
        own = lines.join(labels.hint("shuffle_hash"), "vid", "left" if t is None else "inner")
        one = own.select("l_orderkey", F.col("vid").alias("a"), F.col("label").alias("alabel"))
        other = own.select("l_orderkey", F.col("vid").alias("b"), F.col("label").alias("blabel"))
        return distinct_pairs(one.join(other, "l_orderkey").filter("a < b"), t)

    return told


def _random(k, base):
    """Labels drawn evenly from ``k`` by the md5 of the vertex."""

    def told(t):
        v, e = base(t)
        draw = F.conv(F.substring(F.md5(F.col("vid").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
        return v.select("vid", F.concat(F.lit("L"), (draw % k).cast("string")).alias("label")), e

    return told


def _ranked(base):
    """Labels by their rank: R1 is the most frequent one (of equals, the first by name). The ranking sees one row for each label."""

    def told(t):
        v, e = base(t)
        ranks = v.groupBy("label").agg(F.count("*").alias("n")).select(F.col("label"), F.concat(F.lit("R"), F.row_number().over(Window.orderBy(F.desc("n"), "label")).cast("string")).alias("rank"))
        return v.join(ranks, "label").select("vid", F.col("rank").alias("label")), e

    return told


def _lattice(t):
    """Streets on a grid, with sparse diagonals and a few crossings of both diagonals, which make cliques of four."""
    parts, w = t("part").select("p_partkey"), LATTICE_WIDTH
    inside = F.col("p_partkey") % w != 0
    steps = ((1, inside), (w, F.lit(True)), (w + 1, (F.col("p_partkey") % 7 == 0) & inside), (w - 1, (F.col("p_partkey") % 28 == 1) & (F.col("p_partkey") % w != 1)))
    there = parts.select(F.col("p_partkey").alias("other"))
    e = _union(*[parts.filter(ok).withColumn("other", F.col("p_partkey") + step).join(there, "other").select("p_partkey", "other") for step, ok in steps])
    return _v(parts, key("lattice", "p_partkey"), "*"), _e(e, key("lattice", "p_partkey"), key("lattice", "other"))


def _docs(t):
    docs = t("documents").select("doc_id", "lang", "source", "text")
    sources = dictionary(docs.select("source"))
    hashed = docs.filter("text is not null").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    least = hashed.groupBy("h").agg(F.min("doc_id").alias("least")).filter("least is not null")
    copies = hashed.join(least, "h").filter("doc_id <> least")
    v = _union(_v(docs, key("doc", "doc_id"), F.col("lang")), _v(sources, key("source", "place"), "source"))
    return v, _union(_e(docs.join(sources, "source"), key("doc", "doc_id"), key("source", "place")), _e(copies, key("doc", "doc_id"), key("doc", "least")))


def _web(t):
    pages = t("pages").select("page_id", "url", F.regexp_extract("url", "https?://([^/]+)", 1).alias("host"), F.regexp_extract_all("html", F.lit(HREF), 1).alias("links"))
    each = pages.select("page_id", F.explode("links").alias("link"))
    hosts, links = dictionary(pages.select("host")), dictionary(each.select("link"))
    v = _union(_v(pages, key("page", "page_id"), domain_label("url")), _v(hosts, key("host", "place"), "host"), _v(links, key("link", "place"), "link"))
    return v, _union(_e(pages.join(hosts, "host"), key("page", "page_id"), key("host", "place")), _e(each.join(links, "link"), key("page", "page_id"), key("link", "place")))


#: Vectors of a block; a task holds two blocks.
VECTOR_BLOCK = 16_384


def near_vectors(vectors: DataFrame, least: float, block: int = VECTOR_BLOCK) -> DataFrame:
    """Rows ``(vec_id, other)``, the smaller id first, of all ``(vec_id, embedding)`` whose cosine is at least ``least``: every two blocks meet in a task."""
    blocks = max(1, -(-vectors.count() // block))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    # (low, high): the two blocks that meet; a vector goes to every meeting of its own block
    meeting = F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda x: F.struct(F.least(x, F.col("own")).alias("low"), F.greatest(x, F.col("own")).alias("high"))))
    dealt = vectors.withColumn("own", own).select("vec_id", "embedding", "own", meeting.alias("m")).select("vec_id", "embedding", "own", (F.col("m.low") * F.lit(1 << 32) + F.col("m.high")).alias("place"))

    def met(batches):
        for ids, x, own in _meetings(batches):
            size = np.sqrt((x * x).sum(1, keepdims=True))
            unit = np.divide(x, size, out=np.zeros_like(x), where=size > 0)
            one = own == own[0]
            same = one.all()
            other_ids, other = (ids, unit) if same else (ids[~one], unit[~one])
            ids, unit = ids[one], unit[one]
            for k in range(0, len(ids), 256):
                a, b = np.nonzero(np.round(unit[k : k + 256] @ other.T, 9) >= least)
                u, v = ids[a + k], other_ids[b]
                keep = u < v if same else u != v
                u, v = u[keep], v[keep]
                yield pa.RecordBatch.from_pydict({"vec_id": np.minimum(u, v), "other": np.maximum(u, v)})

    tasks = max(int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(10_000, blocks * (blocks + 1) // 2))
    dealt = dealt.repartition(tasks, "place").sortWithinPartitions("place", "own", "vec_id")
    return dealt.mapInArrow(met, "vec_id long, other long")


def _meetings(batches):
    """``(ids, vectors, blocks)`` of a place after another; places of two blocks of which one is empty are left out."""
    held: list = []

    def told():
        place = held[0][0]
        ids, x, own = (np.concatenate([h[k] for h in held]) for k in (1, 2, 3))
        low, high = divmod(place, 1 << 32)
        return (ids, x, own) if low == high or (own != own[0]).any() else None

    for batch in batches:
        places = batch["place"].to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(places[1:] != places[:-1]) + 1).tolist(), len(places)] if len(places) else []
        for i, j in zip(cuts, cuts[1:]):
            if held and held[0][0] != int(places[i]):
                if (out := told()) is not None:
                    yield out
                held = []
            part = batch.slice(i, j - i)
            x = part["embedding"].flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(j - i, -1)
            held.append((int(places[i]), part["vec_id"].to_numpy(zero_copy_only=False), x, part["own"].to_numpy(zero_copy_only=False)))
    if held and (out := told()) is not None:
        yield out


def _knn(least: float):
    def told(t):
        """Vectors whose cosine is at least ``least``: all against all in blocks, of which a task holds two."""
        vectors = t("embeddings").select("vec_id", "embedding").filter("embedding is not null")
        v = t("embeddings").select(key("vec", "vec_id").alias("vid"), F.concat(F.lit("v"), F.col("label").cast("string")).alias("label"))
        return v, _e(near_vectors(vectors, least), key("vec", "vec_id"), key("vec", "other"))

    return told


def rmat_pairs(spark: SparkSession, scale: int, factor: int, probs: tuple[int, int, int, int], seed: int = 1) -> DataFrame:
    """Recursive quadrants: ``factor * 2**scale`` directed draws ``(a, b)``, each a draw per level from md5, in hundredths."""
    a, b, c, _ = probs
    u, v = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        draw = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}-"), F.col("id").cast("string"), F.lit(f"-{level}")).cast("binary")), 1, 8), 16, 10).cast("long") % 100
        u = u + F.when(draw >= a + b, F.lit(1 << level)).otherwise(F.lit(0))
        v = v + F.when((draw < a) | draw.between(a + b, a + b + c - 1), F.lit(0)).otherwise(F.lit(1 << level))
    return spark.range(factor << scale).select(key("rmat", u).alias("a"), key("rmat", v).alias("b"))


def degree_label(degree: Column | str) -> Column:
    return F.concat(F.lit("d"), F.ceil(F.log2((F.col(degree) if isinstance(degree, str) else degree).cast("double") + 1)).cast("int").cast("string"))


def _rmat(scale: int, factor: int, probs: tuple[int, int, int, int]):
    """Degree classes as labels."""

    def told(t):
        e = materialize(rmat_pairs(SparkSession.getActiveSession(), scale, factor, probs), "rmat")
        return symmetric(e, "a", "b").groupBy("src").agg(F.count("*").alias("n")).select(F.col("src").alias("vid"), degree_label("n").alias("label")), e

    return told


# ---- the oracle's side ----------------------------------------------------------------------------------------------------------


def vid(kind: str, sql: str) -> str:
    return f"({KINDS[kind] << 40} + cast({sql} as bigint))"


def _place(column: str, rows: str) -> str:
    """Values with their place in sorted order."""
    return f"(select {column}, row_number() over (order by {column}) - 1 as place from (select distinct {column} from {rows}) where {column.split(',')[0]} is not null)"


_SQL_TRADE_V = f"""
    select {vid('region', 'r_regionkey')} as vid, 'region' as label from region
    union all select {vid('nation', 'n_nationkey')}, 'nation' from nation
    union all select {vid('customer', 'c_custkey')}, 'cust:' || c_mktsegment from customer
    union all select {vid('supplier', 's_suppkey')}, 'supplier' from supplier
    union all select {vid('part', 'p_partkey')}, 'part:' || p_type from part
    union all select {vid('order', 'o_orderkey')}, 'order:' || o_orderstatus from orders"""
_SQL_TRADE_E = f"""
    select {vid('nation', 'n_nationkey')} as a, {vid('region', 'n_regionkey')} as b from nation
    union all select {vid('customer', 'c_custkey')}, {vid('nation', 'c_nationkey')} from customer
    union all select {vid('supplier', 's_suppkey')}, {vid('nation', 's_nationkey')} from supplier
    union all select {vid('order', 'o_orderkey')}, {vid('customer', 'o_custkey')} from orders
    union all select {vid('order', 'l_orderkey')}, {vid('part', 'l_partkey')} from lineitem
    union all select {vid('order', 'l_orderkey')}, {vid('supplier', 'l_suppkey')} from lineitem
    union all select {vid('part', 'l_partkey')}, {vid('supplier', 'l_suppkey')} from lineitem"""
_SQL_FINE_V = f"""
    select {vid('region', 'r_regionkey')} as vid, 'region' as label from region
    union all select {vid('nation', 'n_nationkey')}, 'nation' from nation
    union all select {vid('customer', 'c_custkey')}, case when c_acctbal > 9000 then 'rich' else 'cust:' || c_mktsegment end from customer
    union all select {vid('supplier', 's_suppkey')}, 'supplier' from supplier
    union all select {vid('part', 'p_partkey')}, 'brand:' || p_brand from part
    union all select {vid('order', 'o_orderkey')}, 'order:' || o_orderstatus from orders"""
_SQL_SHIPPED_E = f"""
    select {vid('order', 'l_orderkey')} as a, {vid('part', 'l_partkey')} as b, l_returnflag as elabel from lineitem
    union all select {vid('order', 'l_orderkey')}, {vid('supplier', 'l_suppkey')}, l_linestatus from lineitem
    union all select {vid('part', 'l_partkey')}, {vid('supplier', 'l_suppkey')}, 'from' from lineitem"""
_SQL_SESSION = (
    f"select {vid('event', 'event_id')} as vid, event_type as label from events union all select distinct {vid('user', 'user_id')}, 'user' from events",
    f"""select {vid('event', 'event_id')} as a, {vid('user', 'user_id')} as b from events
    union all select a, b from (select {vid('event', 'event_id')} as a, lead({vid('event', 'event_id')}) over (partition by user_id order by ts, event_id) as b from events) where b is not null""",
)
_TURNS = "(select *, row_number() over (order by conv_id, turn) - 1 as place from conversations)"
_SQL_CONV = (
    f"select distinct {vid('conversation', 'conv_id')} as vid, 'conv' as label from conversations union all select {vid('turn', 'place')}, role from {_TURNS}",
    f"""select {vid('turn', 'place')} as a, {vid('conversation', 'conv_id')} as b from {_TURNS}
    union all select {vid('turn', 'x.place')}, {vid('turn', 'y.place')} from {_TURNS} x join {_TURNS} y on x.conv_id = y.conv_id and y.turn = x.turn + 1""",
)
_OWN = "(select distinct l_orderkey, l_partkey from lineitem)"
_SQL_COORDER_E = f"select distinct {vid('part', 'x.l_partkey')} as a, {vid('part', 'y.l_partkey')} as b from {_OWN} x join {_OWN} y on x.l_orderkey = y.l_orderkey and x.l_partkey < y.l_partkey"


def _sql_coorder(label: str) -> tuple[str, str]:
    return f"select {vid('part', 'p_partkey')} as vid, {label} as label from part", _SQL_COORDER_E


def _sql_random(k: int) -> tuple[str, str]:
    v, e = _sql_coorder("'*'")
    return f"select vid, 'L' || (cast('0x' || substr(md5(cast(vid as varchar)), 1, 8) as bigint) % {k}) as label from ({v})", e


def _sql_ranked(base: tuple[str, str]) -> tuple[str, str]:
    v, e = base
    return f"select vid, 'R' || k as label from ({v}) v0 join (select label as own, row_number() over (order by count(*) desc, label) as k from ({v}) group by label) r0 on label = own", e


_SQL_LATTICE = (
    f"select {vid('lattice', 'p_partkey')} as vid, '*' as label from part",
    " union all ".join(
        f"select {vid('lattice', 'x.p_partkey')} as a, {vid('lattice', 'y.p_partkey')} as b from part x join part y on y.p_partkey = x.p_partkey + {step} where {rule}"
        for step, rule in ((1, f"x.p_partkey % {LATTICE_WIDTH} <> 0"), (LATTICE_WIDTH, "true"), (LATTICE_WIDTH + 1, f"x.p_partkey % 7 = 0 and x.p_partkey % {LATTICE_WIDTH} <> 0"), (LATTICE_WIDTH - 1, f"x.p_partkey % 28 = 1 and x.p_partkey % {LATTICE_WIDTH} <> 1"))
    ),
)
_SOURCES = _place("source", "documents")
_SQL_DOCS = (
    f"select {vid('doc', 'doc_id')} as vid, lang as label from documents union all select {vid('source', 'place')}, 'source' from {_SOURCES}",
    f"""select {vid('doc', 'd.doc_id')} as a, {vid('source', 's.place')} as b from documents d join {_SOURCES} s on d.source = s.source
    union all select {vid('doc', 'x.doc_id')}, {vid('doc', 'y.least')} from documents x join (select text, min(doc_id) as least from documents group by text) y on x.text = y.text where x.doc_id <> y.least""",
)
_LINKS = f"(select page_id, unnest(regexp_extract_all(html, '{HREF}', 1)) as link from pages)"
_HOSTED = "(select page_id, regexp_extract(url, 'https?://([^/]+)', 1) as host from pages)"


def sql_domain_label(url: str) -> str:
    host = f"lower(regexp_extract({url}, '^[a-z]+://([^/:?#]+)', 1))"
    parts, second = f"string_split({host}, '.')", ", ".join(f"'{x}'" for x in SECOND_LEVEL)
    return f"case when {host} = '' then null when len({parts}) > 2 and {parts}[-2] in ({second}) then '.' || {parts}[-2] else '.' || {parts}[-1] end"


_SQL_WEB = (
    f"""select {vid('page', 'page_id')} as vid, {sql_domain_label('url')} as label from pages
    union all select {vid('host', 'place')}, 'host' from {_place('host', _HOSTED)} union all select {vid('link', 'place')}, 'link' from {_place('link', _LINKS)}""",
    f"""select {vid('page', 'p.page_id')} as a, {vid('host', 'h.place')} as b from {_HOSTED} p join {_place('host', _HOSTED)} h on p.host = h.host
    union all select {vid('page', 'p.page_id')}, {vid('link', 'h.place')} from {_LINKS} p join {_place('link', _LINKS)} h on p.link = h.link""",
)


def _sql_knn(least: float) -> tuple[str, str]:
    return (
        f"select {vid('vec', 'vec_id')} as vid, 'v' || label as label from embeddings",
        f"select {vid('vec', 'x.vec_id')} as a, {vid('vec', 'y.vec_id')} as b from embeddings x join embeddings y on x.vec_id < y.vec_id where round(list_cosine_similarity(x.embedding::double[], y.embedding::double[]), 9) >= {least}",
    )


def sql_rmat(scale: int, factor: int, probs: tuple[int, int, int, int], seed: int = 1) -> str:
    a, b, c, _ = probs
    draw = f"(cast('0x' || substr(md5('{seed}-' || e || '-' || level), 1, 8) as bigint) % 100)"
    return f"""select {vid('rmat', 'u')} as a, {vid('rmat', 'v')} as b from (select e, sum(case when r >= {a + b} then (1::bigint << level) else 0 end) as u,
    sum(case when r < {a} or (r >= {a + b} and r < {a + b + c}) then 0 else (1::bigint << level) end) as v
    from (select e, level, {draw} as r from (select range as e from range({factor << scale})), (select range as level from range({scale}))) group by e)"""


def _sql_rmat(scale: int, factor: int, probs: tuple[int, int, int, int]) -> tuple[str, str]:
    e = sql_rmat(scale, factor, probs)
    both = f"(select a, b from ({e}) where a <> b union select b, a from ({e}) where a <> b)"
    return f"select a as vid, 'd' || cast(ceil(log2(count(*) + 1)) as int) as label from {both} group by a", e


_STAR = lambda: F.lit("*")
_TYPE = lambda: F.col("p_type")
_BRAND = lambda: F.col("p_brand")
#: name: (Spark, oracle)
GRAPHS: dict[str, tuple[Callable, tuple[str, str]]] = {
    "trade": (_trade, (_SQL_TRADE_V, _SQL_TRADE_E)), "trade_fine": (_trade_fine, (_SQL_FINE_V, _SQL_TRADE_E)), "shipped": (_shipped, (_SQL_TRADE_V, _SQL_SHIPPED_E)), "session": (_session, _SQL_SESSION), "conv": (_conv, _SQL_CONV),
    "docs": (_docs, _SQL_DOCS), "web": (_web, _SQL_WEB), "knn": (_knn(0.35), _sql_knn(0.35)), "lattice": (_lattice, _SQL_LATTICE),
    "coorder": (_coorder(_STAR), _sql_coorder("'*'")), "coorder_typed": (_coorder(_TYPE), _sql_coorder("p_type")), "coorder_branded": (_coorder(_BRAND), _sql_coorder("p_brand")),
    "random25": (_random(25, _coorder(_STAR)), _sql_random(25)), "random50": (_random(50, _coorder(_STAR)), _sql_random(50)), "random100": (_random(100, _coorder(_STAR)), _sql_random(100)),
    "session_ranked": (_ranked(_session), _sql_ranked(_SQL_SESSION)),
}
#: Graphs whose edges can be labelled by kind, and picked by a template before they are dealt.
LABELLED: dict[str, Callable] = {"trade": _trade_labelled, "coorder": _coorder_labelled(_STAR), "coorder_typed": _coorder_labelled(_TYPE), "coorder_branded": _coorder_labelled(_BRAND)}
#: Probabilities of the quadrants, in hundredths.
RMAT = {"rmat_skewed": (57, 19, 19, 5), "rmat_mild": (45, 15, 15, 25), "rmat_even": (25, 25, 25, 25)}
RMAT_SCALE, RMAT_FACTOR = 10, 16
GRAPHS |= {k: (_rmat(RMAT_SCALE, RMAT_FACTOR, p), _sql_rmat(RMAT_SCALE, RMAT_FACTOR, p)) for k, p in RMAT.items()}


def fill(text: str, spark: SparkSession | None = None, sf_dir: str | None = None) -> DataFrame | str:
    """A statement with table names in braces: run by Spark on the Parquet files, or as text for the oracle."""
    names = [f for _, f, _, _ in string.Formatter().parse(text) if f]
    if spark is None:
        return text.format(**{n: n for n in names})
    return spark.sql(text, **{n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in dict.fromkeys(names)})


def _stored(v: DataFrame, e: DataFrame, name: str) -> LabeledGraph:
    return LabeledGraph(v, materialize(e.sortWithinPartitions("slabel", "dlabel"), f"{name}-e"))


def store(vertices: DataFrame, edges: DataFrame, name: str) -> LabeledGraph:
    """A graph written for searches: edges (symmetric, with the ends' labels beside them) lie sorted by those labels, so that a template's scan
    skips the row groups of others. Metadata is read once, here; ends without a vertex row have a null label."""
    v = materialize(vertices, f"{name}-v")
    e = edges.join(v.select(F.col("vid").alias("src"), F.col("label").alias("slabel")), "src", "left").join(v.select(F.col("vid").alias("dst"), F.col("label").alias("dlabel")), "dst", "left")
    more = [c for c in ("elabel", "forward") if c in edges.columns]
    return _stored(v, e.select("src", "dst", "slabel", "dlabel", *more), name)


def both_ways(e: DataFrame) -> DataFrame:
    """``(src, dst, slabel, dlabel)`` from ``(a, b, alabel, blabel)``, which are read once."""
    way = lambda a, b: F.struct(F.col(a).alias("src"), F.col(b).alias("dst"), F.col(f"{a}label").alias("slabel"), F.col(f"{b}label").alias("dlabel"))
    return e.select(F.inline(F.array(way("a", "b"), way("b", "a"))))


def build(spark: SparkSession, sf_dir: str, name: str, t: Template | None = None) -> LabeledGraph:
    """The graph, stored. With a template and where the graph can be read by kind (``LABELLED``): only the edges that the template's may be, read from
    the tables when a search writes its candidates, and not stored besides."""
    tables = lambda table: spark.read.parquet(f"{sf_dir}/{table}.parquet")
    v, e = GRAPHS[name][0](tables)
    if name in LABELLED:
        e = both_ways(LABELLED[name](tables, t))
        return _stored(materialize(v, f"{name}-v"), e, name) if t is None else LabeledGraph(v, e)
    return store(v, labelled_edges(e, F.col("elabel"), "a", "b") if "elabel" in e.columns else symmetric(e, "a", "b"), name)


def free(g: LabeledGraph) -> None:
    discard(g.vertices)
    discard(g.edges)


def oracle_prefix(name: str) -> str:
    """``gv(vid, label)`` and ``ge(src, dst)`` (labelled: ``ge(src, dst, elabel, forward)``) as common table expressions for the oracle."""
    v, e = GRAPHS[name][1]
    if "elabel" in e:
        return f"gv as materialized ({v}), g0 as materialized ({e}), ge as materialized (select a as src, b as dst, elabel, true as forward from g0 where a <> b union select b, a, elabel, false from g0 where a <> b)"
    return f"gv as materialized ({v}), g0 as materialized ({e}), ge as materialized (select a as src, b as dst from g0 where a <> b union select b, a from g0 where a <> b)"


def _oracle_edges(name: str, t: Template, a: int, b: int) -> str:
    """The data edges that template edge a-b may be, run from a to b."""
    tests = [f"x.label = '{t.labels[a]}'", f"y.label = '{t.labels[b]}'"]
    if "elabel" in GRAPHS[name][1][1]:
        for p, q, label, way in t.demands:
            if {p, q} == {a, b}:
                tests += [f"elabel = '{label}'"] * (label is not None) + ["forward" if p == a else "not forward"] * way
    return f"select distinct src, dst from ge join gv x on x.vid = src join gv y on y.vid = dst where {' and '.join(tests)}"


def oracle_matches(name: str, t: Template, mapped: str = "m") -> str:
    """The prefix and all embeddings of a template, by plain joins of edge sets, a role at a time.

    Every step is a table of its own: left to itself the oracle's planner may start with edges that have no role in common, and fill the disk.
    """
    if t.n == 1:
        return f"with {oracle_prefix(name)}, {mapped} as (select vid as r0 from gv where label = '{t.labels[0]}')"
    order = list(t.edges[0]) if t.edges else [0]
    tables = [f"{mapped}_{a}_{b} as materialized ({_oracle_edges(name, t, a, b)})" for a, b in t.edges]
    edge = lambda a, b: (f"{mapped}_{a}_{b}", "src", "dst") if (a, b) in t.edges else (f"{mapped}_{b}_{a}", "dst", "src")
    first = edge(*order)
    differ = " where src <> dst" if t.labels[order[0]] == t.labels[order[1]] else ""
    steps = [f"select {first[1]} as r{order[0]}, {first[2]} as r{order[1]} from {first[0]}{differ}"]
    while len(order) < t.n:
        q = max((x for x in range(t.n) if x not in order), key=lambda x: (len(t.adjacent[x] & set(order)), -x))
        at, *more = sorted(t.adjacent[q] & set(order))
        held = ", ".join(f"p.r{x}" for x in order)
        e = edge(at, q)
        joins = f"join {e[0]} e on e.{e[1]} = p.r{at}" + "".join(f" join {c[0]} c{x} on c{x}.{c[1]} = p.r{x} and c{x}.{c[2]} = e.{e[2]}" for x in more for c in [edge(x, q)])
        apart = "".join(f" and e.{e[2]} <> p.r{x}" for x in order if t.labels[x] == t.labels[q])
        steps.append(f"select {held}, e.{e[2]} as r{q} from {{before}} p {joins} where true{apart}")
        order.append(q)
    for k, step in enumerate(steps):
        own = mapped if k == len(steps) - 1 else f"{mapped}__{k}"
        tables.append(f"{own} as materialized ({step.format(before=f'{mapped}__{k - 1}')})")
    return f"with {oracle_prefix(name)}, {', '.join(tables)}"
