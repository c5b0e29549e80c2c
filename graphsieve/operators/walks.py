"""Walk checks with folded tokens, and the confirmation of roles and edges by walking back.

A token is a row with a column for each position that is still read. Its first hop is a filter of the edges; every other one is a join,
the tests of chords, and a distinct over the live positions. Where tokens are many, a step with a chord joins them to the paths between both ends
instead (``meet``), so that what does not close is never made. Vertices of very many edges (hubs) get a salt on both sides of
the join, so that a hub's edges are spread over tasks, and the distinct that follows has another key than the join.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from graphsieve.functions.storage import discard, written
from graphsieve.operators.cliques import listed
from graphsieve.operators.dealt import dealt_walk, layout, moved_ends
from graphsieve.operators.reduce import State, apply_masks, both_ways, has, plays
from graphsieve.plans.rules import Rule, Step, WalkPlan, best_start, known_pairs, lone_pair
from graphsieve.plans.template import Template

#: A hub has this many edges, and so many salts; a state of fewer edges than HUB_FROM is not searched for hubs.
HUB_DEGREE, HUB_SALTS, HUB_FROM = 500_000, 64, 20_000_000


def _p(q: int) -> str:
    return f"p{q}"


def hubs_of(state: State, degree: int = HUB_DEGREE, least: int = HUB_FROM) -> DataFrame | None:
    """``(hub)``: vertices of at least ``degree`` edges, or none. There are at most rows / degree of them, so they can be broadcast."""
    degree = max(degree, state.rows // 10_000)
    if state.rows < least:
        return None
    found, seen = written(state.edges.groupBy("src").agg(F.count("*").alias("_n")).filter(F.col("_n") >= degree).select(F.col("src").alias("hub")), "hubs")
    return found if seen["rows"] else None


def begin(state: State, plan: WalkPlan) -> DataFrame:
    """Tokens at the vertices that may play the first role."""
    return state.masks.filter(has("mask", plan.start)).select(F.col("vid").alias(_p(plan.start)))


def extend(tokens: DataFrame, edges: DataFrame, step: Step, t: Template, hubs: DataFrame | None = None, salts: int = HUB_SALTS) -> DataFrame:
    """Tokens after a step, all positions kept: a join to the active edges, or (chord) a semi-join on both ends."""
    e = edges.filter(plays(t, step.at, step.to)).select(F.col("src").alias(_p(step.at)), F.col("dst").alias(_p(step.to)))
    if step.chord:
        return tokens.join(e, [_p(step.at), _p(step.to)], "left_semi")
    if hubs is None:
        out = tokens.join(e, _p(step.at))
    else:  # at most 10,000 hubs, see hubs_of
        h = F.broadcast(hubs.withColumnRenamed("hub", _p(step.at)).withColumn("_hub", F.lit(True)))
        e = e.join(h, _p(step.at), "left").withColumn("_salt", F.when(F.col("_hub"), F.pmod(F.xxhash64(_p(step.to)), F.lit(salts)).cast("int")).otherwise(F.lit(0))).drop("_hub")
        all_salts = F.sequence(F.lit(0), F.lit(salts - 1))
        tokens = tokens.join(h, _p(step.at), "left").withColumn("_salt", F.explode(F.when(F.col("_hub"), all_salts).otherwise(F.array(F.lit(0))))).drop("_hub")
        out = tokens.join(e, [_p(step.at), "_salt"]).drop("_salt")
    return _tested(out, step)


def meet(tokens: DataFrame, edges: DataFrame, step: Step, t: Template) -> DataFrame:
    """Tokens after a step that closes a cycle at once: paths over the new role, from the step's place to ``step.over``, meet tokens that hold both ends."""
    half = lambda q: edges.filter(plays(t, q, step.to)).select(F.col("src").alias(_p(q)), F.col("dst").alias(_p(step.to)))
    return _tested(tokens.join(half(step.at).join(half(step.over), _p(step.to)), [_p(step.at), _p(step.over)]), step)


def _tested(tokens: DataFrame, step: Step) -> DataFrame:
    tests = [F.col(_p(step.to)) != F.col(_p(x)) for x in step.differs] + [F.col(_p(i)) < F.col(_p(j)) for i, j in step.below]
    return tokens.filter(reduce(lambda a, b: a & b, tests)) if tests else tokens


def hop(tokens: DataFrame | None, state: State, move: tuple[Step, tuple[Step, ...]], hubs: DataFrame | None = None, sources=None) -> DataFrame:
    """One extension and its chords. Without tokens it is the first hop: the edges themselves. ``sources`` filters its start."""
    step, chords = move
    t = state.template
    if tokens is None:
        out = _tested(state.edges.filter(plays(t, step.at, step.to)).select(F.col("src").alias(_p(step.at)), F.col("dst").alias(_p(step.to))), step)
        out = out if sources is None else out.filter(sources(_p(step.at)))
    elif step.over is not None:
        out = meet(tokens, state.edges, step, t)
    else:
        out = extend(tokens, state.edges, step, t, hubs)
    for c in chords:
        if c.at != step.over:
            out = extend(out, state.edges, c, t)
    return out


def fold(tokens: DataFrame, live: tuple[int, ...], how: str = "live") -> DataFrame:
    """One copy of tokens that are alike in all that is read later; with no folding dead positions stay."""
    if how == "none":
        return tokens
    return tokens.select(*map(_p, live)).distinct() if live else tokens.select(F.lit(1).alias("some")).distinct()


def _folded(wide: DataFrame, live: tuple[int, ...], how: str) -> tuple[DataFrame, int, int]:
    """Folded tokens, written, with the number of those that came and of those that are left."""
    if how == "none":
        tokens, n = written(wide, "tokens")
        return tokens, n["rows"], n["rows"]
    came = Observation()
    tokens, n = written(fold(wide.observe(came, F.count(F.lit(1)).alias("rows")), live, how), "tokens")
    return tokens, came.get["rows"] if n["rows"] else 0, n["rows"]  # where nothing comes, the count may have been planned away


def _shares(buckets: int):
    """Filters that part the sources, one pass each."""
    if buckets <= 1:
        return [None]
    return [lambda c, b=b: F.pmod(F.xxhash64(c), F.lit(buckets)) == b for b in range(buckets)]


def rule_plan(t: Template, rule: Rule, how: str = "live", frequency: dict | None = None) -> WalkPlan:
    """The walk of a rule from its start. ``issuer``: tokens that carry their start and last position and no more, which needs a cycle or path
    whose roles (but for a path's ends) have different labels, walked in order; refused elsewhere."""
    if how not in ("live", "none", "issuer"):
        raise ValueError("how is live, none or issuer")
    sequence = None
    if how == "issuer":
        if rule.kind == "cover" or len({t.labels[q] for q in rule.roles}) < len(rule.roles) - (rule.kind == "path"):
            raise ValueError("tokens that carry only their issuer are unsafe for this rule")
        sequence = rule.sequence()
    return WalkPlan(t, rule.edges, rule.start, frequency, keep=(rule.start,), sequence=sequence)


def walk_sources(state: State, rule: Rule, how: str = "live", frequency: dict | None = None, buckets: int = 1, hubs: DataFrame | None = None, seen: list | None = None) -> DataFrame:
    """``(vid)``: vertices from which the rule's walk completes in the role it starts from.

    ``buckets`` walks the sources in so many passes, which divides the tokens in flight; each pass is written before the next begins.
    ``seen``: a list that gets the tokens that come with every hop, and those that are left once folded (the hops are then written, to be counted).
    """
    plan = rule_plan(state.template, rule, how, frequency)
    found = []
    for share in _shares(buckets):
        tokens = None
        for k, move in enumerate(plan.hops):
            live = tuple(sorted({*(move[1][-1] if move[1] else move[0]).live, rule.start}))
            wide = hop(tokens, state, move, hubs, share)
            if seen is None:
                tokens = fold(wide, live, how)
            else:
                before = tokens
                tokens, came, left = _folded(wide, live, how)
                discard(before)
                seen.append({"hop": k + 1, "came": came, "tokens": left})
        out = tokens.select(F.col(_p(rule.start)).alias("vid")).distinct()
        found.append(out if buckets == 1 else written(out, "sources")[0])
    return reduce(DataFrame.unionByName, found)


def walk_check(state: State, rule: Rule, how: str = "live", frequency: dict | None = None, buckets: int = 1, hubs: DataFrame | None = None, seen: dict | None = None) -> tuple[State, dict]:
    """Vertices without a completed walk lose the role that the rule starts from. ``seen`` gets the tokens that came with all hops, and the walks that they completed."""
    counted = None if seen is None else []
    dealt = dealt_walk(state, rule.edges, rule_plan(state.template, rule, how, frequency), how, frequency, False) if buckets == 1 else None
    if dealt is None:
        good = walk_sources(state, rule, how, frequency, buckets, hubs, counted)
    else:
        good, came, walks = dealt
    good = good.withColumn("_good", F.lit(True))
    gone = F.bitwise_not(F.lit(1 << rule.start).cast("long"))
    masks = state.masks.join(good, "vid", "left").select("vid", "mask", F.when(F.col("_good"), F.col("mask")).otherwise(F.col("mask").bitwiseAND(gone)).alias("new"))
    if seen is not None and dealt is not None:
        seen |= {"tokens": seen.get("tokens", 0) + came, "walks": seen.get("walks", 0) + walks}
    elif seen is not None:
        last = max(x["hop"] for x in counted)
        seen["tokens"] = seen.get("tokens", 0) + sum(x["came"] for x in counted)
        seen["walks"] = seen.get("walks", 0) + sum(x["came"] for x in counted if x["hop"] == last)
    return apply_masks(state, masks)


def _dealt_pairs(state: State, edges, frequency: dict, how: str) -> tuple[DataFrame, int, int] | None:
    """Pairs by walks that are dealt by their sources, from the role whose walks stay nearest; none if joins had better do it."""
    t, found = state.template, []
    if not known_pairs(t, frequency):
        return None
    for start in sorted({x for e in edges for x in e}):
        plan = WalkPlan(t, edges, start, frequency)
        if (planned := layout(edges, plan)) is not None:
            found.append((moved_ends(t, frequency, plan, *planned), start, plan))
    return dealt_walk(state, edges, min(found, key=lambda x: x[:2])[2], how, frequency, True) if found else None


def _every_pair(state: State, edges, frequency: dict, buckets: int, hubs: DataFrame | None, seen: dict | None) -> DataFrame:
    """``confirmed_pairs`` without folding: tokens carry all their positions, so those that complete tell the pairs, and there is no way back."""
    t = state.template
    plan, pairs, tokens, walks = WalkPlan(t, edges, best_start(t, edges, frequency), frequency), [], 0, 0
    ends = F.array(*[F.struct(F.lit(s.at).alias("a"), F.lit(s.to).alias("b"), F.col(_p(s.at)).alias("u"), F.col(_p(s.to)).alias("v")) for s in plan.steps])
    for share in _shares(buckets):
        wide = None
        for move in plan.hops:
            before = wide
            wide, came = written(hop(before, state, move, hubs, share), "tokens")
            discard(before)
            tokens += came["rows"]
        pairs.append(written(wide.select(F.inline(ends)).distinct(), "pairs")[0])
        discard(wide)
        walks += came["rows"]
    if seen is not None:
        seen |= {"tokens": seen.get("tokens", 0) + tokens, "walks": seen.get("walks", 0) + walks}
    return reduce(DataFrame.unionByName, pairs)


def confirmed_pairs(state: State, edges, frequency: dict | None = None, buckets: int = 1, hubs: DataFrame | None = None, seen: dict | None = None, how: str = "live") -> DataFrame:
    """``(a, b, u, v)``: of the given template edges, a-b is played by data edge u-v in at least one walk over all of them.

    Forward, each hop's expansion is written once; the next hop reads it folded. Backward, the rows of an expansion are kept that a kept
    class of the next one stands for. They come from before the fold, so no prefix of a completed walk is lost.

    A vertex that is carried only to differ from one later role (``lone_pair``) is folded too: of all such vertices the least and the greatest stay, as
    one of them differs from whatever comes. Backward, the least and the greatest of the later role tell which of the vertices had one to differ from.
    """
    t, freq = state.template, frequency or {}
    if buckets == 1 and (dealt := _dealt_pairs(state, edges, freq, how)) is not None:
        pairs, tokens, walks = dealt
        if seen is not None:
            seen |= {"tokens": seen.get("tokens", 0) + tokens, "walks": seen.get("walks", 0) + walks}
        return pairs
    if how == "none":
        return _every_pair(state, edges, freq, buckets, hubs, seen)
    pair = lone_pair(t, edges)
    plan = WalkPlan(t, edges, best_start(t, edges, freq, two=pair is not None), freq, two=pair is not None)
    lives = [(m[1][-1] if m[1] else m[0]).live for m in plan.hops]
    x, y = sorted(pair, key=plan.roles.index) if pair else (None, None)
    read = [{s.at for m in plan.hops[k + 1 :] for s in (m[0], *m[1])} for k in range(len(plan.hops))]
    # hops after which x is there only to differ from y
    spare = [pair is not None and x in lives[k] and x not in read[k] and any(m[0].to == y for m in plan.hops[k + 1 :]) for k in range(len(plan.hops))]
    others = [[_p(q) for q in live if q != x] for live in lives]
    pairs, counted, walks = [], 0, 0
    for share in _shares(buckets):
        wides, tokens = [], None
        for k, (move, live) in enumerate(zip(plan.hops, lives)):
            wide, n = written(hop(tokens, state, move, hubs, share), "walk")
            counted += n["rows"]
            wides.append(wide)
            if spare[k]:
                two = wide.groupBy(*others[k]).agg(F.array_distinct(F.array(F.min(_p(x)), F.max(_p(x)))).alias("_two"))
                tokens = two.select(*others[k], F.explode("_two").alias(_p(x)))
            else:
                tokens = fold(wide, live)
        kept, walks = wides[-1], walks + n["rows"]
        for k in range(len(plan.hops) - 1, -1, -1):
            step, chords = plan.hops[k]
            if k < len(plan.hops) - 1:
                if spare[k]:
                    low, high = (_p(y), _p(y)) if plan.hops[k + 1][0].to == y else ("_low", "_high")
                    ends = kept.groupBy(*others[k]).agg(F.min(low).alias("_low"), F.max(high).alias("_high"))
                    kept, _ = written(wides[k].join(ends, others[k]).filter((F.col(_p(x)) != F.col("_low")) | (F.col(_p(x)) != F.col("_high"))), "back")
                elif lives[k]:
                    kept, _ = written(wides[k].join(kept.select(*map(_p, lives[k])).distinct(), [*map(_p, lives[k])], "left_semi"), "back")
                elif kept.isEmpty():
                    kept = wides[k].limit(0)
                else:
                    kept = wides[k]
            for s in (step, *chords):
                pairs.append(kept.select(F.lit(s.at).alias("a"), F.lit(s.to).alias("b"), F.col(_p(s.at)).alias("u"), F.col(_p(s.to)).alias("v")).distinct())
    if seen is not None:
        seen |= {"tokens": seen.get("tokens", 0) + counted, "walks": seen.get("walks", 0) + walks}
    return reduce(DataFrame.unionByName, pairs)


def _roles(pairs: DataFrame) -> DataFrame:
    """``(vid, good)``: roles that a vertex plays in some pair."""
    both = pairs.select(F.explode(F.array(F.struct(F.col("u").alias("vid"), F.col("a").alias("q")), F.struct(F.col("v").alias("vid"), F.col("b").alias("q")))).alias("x"))
    return both.select("x.*").groupBy("vid").agg(F.bit_or(F.expr("shiftleft(1L, q)")).alias("good"))


def rule_check(state: State, rule: Rule, frequency: dict | None = None, buckets: int = 1, hubs: DataFrame | None = None, seen: dict | None = None) -> tuple[State, dict]:
    """A walk of the rule, forward and back, settles all its roles at once: as if walked from every role in turn."""
    pairs, _ = written(confirmed_pairs(state, rule.edges, frequency, buckets, hubs, seen), "pairs")
    inside = sum(1 << q for q in rule.roles)
    kept = F.col("mask").bitwiseAND(F.bitwise_not(F.lit(inside).cast("long"))).bitwiseOR(F.col("mask").bitwiseAND(F.coalesce("good", F.lit(0).cast("long"))))
    out = apply_masks(state, state.masks.join(_roles(pairs), "vid", "left").select("vid", "mask", kept.alias("new")))
    discard(pairs)
    return out


def _confirm_clique(state: State, seen: dict | None = None) -> State:
    """All roles are alike, so each set of vertices is listed once; its members play every role. Wedges are made and closed within tasks."""
    t = state.template
    found, n = written(listed_cliques(state), "cliques")
    ends = F.array(*[F.struct(F.col(f"c{a}").alias("src"), F.col(f"c{b}").alias("dst")) for b in range(t.n) for a in range(b)])
    every = F.lit((1 << t.n) - 1).cast("long")
    e, kept = written(both_ways(found.select(F.inline(ends)).distinct().select("src", "dst", every.alias("smask"), every.alias("dmask"))), "confirmed")
    if not state.borrowed:
        discard(state.edges)
    out = State(t, e, kept["rows"], None, state.trace, matches=found)
    if seen is not None:
        seen |= {"tokens": seen.get("tokens", 0) + n["rows"], "walks": seen.get("walks", 0) + n["rows"], "alive": out.counts()[0]}
    return out


def listed_cliques(state: State) -> DataFrame:
    """``(c0 < c1 < ...)``: vertex sets of the matches of a clique of one label."""
    return listed(state.edges.select("src", "dst"), state.template.n)


def confirm(state: State, frequency: dict | None = None, buckets: int = 1, hubs: DataFrame | None = None, seen: dict | None = None, how: str = "live") -> State:
    """The exact answer: roles and edges that take part in a match. ``how``: live or none, as tokens are folded."""
    t = state.template
    if t.n == 1 or not state.rows:
        return state
    if t.one_label_clique:
        return _confirm_clique(state, seen)
    pairs, _ = written(confirmed_pairs(state, t.edges, frequency, buckets, hubs, seen, how), "pairs")
    masks, alive = written(_roles(pairs), "roles")
    e = pairs.select("u", "v").unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct().select(F.col("u").alias("src"), F.col("v").alias("dst"))
    e = e.join(masks.select(F.col("vid").alias("src"), F.col("good").alias("smask")), "src").join(masks.select(F.col("vid").alias("dst"), F.col("good").alias("dmask")), "dst")
    if t.demands:
        e = e.join(state.edges.select("src", "dst", "allow"), ["src", "dst"])
    e, kept = written(e.select("src", "dst", "smask", "dmask", *(["allow"] if t.demands else [])), "confirmed")
    discard(pairs)
    if not state.borrowed:
        discard(state.edges)
    if seen is not None:
        seen["alive"] = alive["rows"]
    return State(t, e, kept["rows"], None, state.trace)
