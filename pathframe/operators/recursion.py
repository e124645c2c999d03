"""The recursive operator in five semantics, bounded walks of the k best, and baselines of the fixpoint itself.

Every round joins the newest paths with the step relation on last = first and keeps what the mode allows. The step
relation and each round's rows are written to the session's shared folder, which cuts the lineage and keeps plans as
small in the last round as in the first; a round is counted as it is written, to see whether anything is left. Nothing
is cached, so nothing is left behind in executors, and a lost one costs no more than its tasks.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import paths as P
from ..sources.shared import written
from . import search
from .pathset import Facts, PathSet, least_per_pair

MODES = ("walk", "trail", "acyclic", "simple", "shortest")
#: What other path languages fix as their only semantics.
PRESETS = {"arbitrary": "walk", "acyclic": "acyclic", "trail": "trail", "shortest": "shortest"}
#: Rows that one round may keep before the recursion is refused.
BUDGET = 2_000_000_000


class InfiniteWalkError(ValueError):
    """A recursion without end: walks over a cycle, with neither a length bound nor a bounding selector."""


class BudgetError(RuntimeError):
    """A round made more rows than allowed; nothing is cut off silently."""


@dataclass
class Log:
    """Rounds of one recursion: (round, rows kept), the longest path of each, and how it ended; with detail, of each
    round also the pairs that met, and those of them that the mode pruned or that were there before."""

    rounds: list[tuple[int, int]] = field(default_factory=list)
    ended: str = ""
    detail: bool = False
    longest: list[int] = field(default_factory=list)
    met: dict[int, int] = field(default_factory=dict)
    pruned: dict[int, int] = field(default_factory=dict)
    repeated: dict[int, int] = field(default_factory=dict)


def _keep(df: DataFrame, level: int, log: Log) -> tuple[DataFrame, int]:
    longest = F.max("len" if "len" in df.columns else F.lit(0))
    df, seen = written(df, n=F.count(F.lit(1)), longest=longest)
    log.rounds.append((level, seen["n"]))
    log.longest.append(seen["longest"] or 0)
    if seen["n"] > BUDGET:
        raise BudgetError(f"round {level} made {seen['n']} paths, more than {BUDGET}")
    return df, seen["n"]


def _seeded(df: DataFrame, seed) -> DataFrame:
    """Rows that start in seed: a list of ids (small), or a table whose first column has them."""
    if seed is None:
        return df
    if isinstance(seed, DataFrame):
        return df.join(seed.select(F.col(seed.columns[0]).alias("__seed")).distinct(), F.col("src") == F.col("__seed"), "left_semi")
    return df.filter(F.col("src").isin(list(seed)))


def recurse(paths: PathSet, mode: str = "walk", *, seed=None, direction: str = "forward", max_len: int | None = None, keep: tuple[str, int] | None = None, strategy: str = "seminaive", log: Log | None = None) -> PathSet:
    """One or more: all lawful concatenations of paths of the set.

    seed: first nodes (last nodes when direction is "backward") to start from; the step relation stays whole.
    max_len: edges of a whole path, at most. keep: ("k_shortest", k) or ("k_lengths", k) for walks, by pair of ends.
    Walks without a bound are refused when the graph of the steps has a cycle that the seed can reach.
    Shortest walks of all pairs over single edges are searched for in tasks that hold the edges (search.py), unless
    these are very many or a log of rounds is asked for.
    """
    searched = log is None and seed is None and max_len is None and strategy == "seminaive" and (keep == ("k_shortest", 1) and mode == "walk" or keep is None and PRESETS.get(mode, mode) == "shortest")
    log = log if log is not None else Log()
    mode = PRESETS.get(mode, mode)
    if mode not in MODES:
        raise ValueError(f"no path mode {mode!r}")
    if direction == "backward":
        return recurse(paths.reversed(), mode, seed=seed, max_len=max_len, keep=keep, strategy=strategy, log=log).reversed()
    base = paths.distinct()
    if searched and base.facts.uniform and base.facts.least == 1:
        df, seen = written(base.df, n=F.count(F.lit(1)))
        base = replace(base, df=df)
        if seen["n"] <= search.HELD:
            return PathSet(search.shortest_of_all(df, one=keep is not None), base.graph, _facts(base, max_len))
    zero = _seeded(base.df.filter("len = 0"), seed) if base.facts.least == 0 else None
    steps = replace(base, df=_kept(base.df.filter("len > 0") if zero is not None else base.df), facts=replace(base.facts, least=max(1, base.facts.least)))
    if keep is not None:
        if mode != "walk":
            raise ValueError("the k best are kept of walks only; restricted walks aren't closed under it")
        out = _k_best(steps, seed, keep, max_len, log)
    elif mode == "shortest":
        out = _shortest(steps, seed, max_len, log)
    else:
        if mode == "walk" and max_len is None:
            refuse_cycles(steps, seed)
        out = _naive(steps, mode, seed, max_len, log) if strategy == "naive" else _grow(steps, mode, seed, max_len, log)
    if zero is None:
        return out
    return PathSet(zero, paths.graph, Facts(0, 0, True)).union(out)


def _kept(df: DataFrame) -> DataFrame:
    """A relation that every round reads."""
    return written(df)[0]


def _step_side(steps: PathSet, mode: str) -> DataFrame:
    return steps.df if mode == "walk" else _kept(steps.df if mode == "shortest" else steps.df.filter(P.LAWFUL[mode]()))


def _facts(steps: PathSet, max_len: int | None) -> Facts:
    return Facts(steps.facts.least, max_len, True, steps.facts.labels)


def _extend(delta: DataFrame, step: DataFrame, mode: str, max_len: int | None, log: Log | None = None, level: int = 0) -> DataFrame:
    a, b = delta.alias("a"), step.alias("b")
    on = F.col("a.dst") == F.col("b.src")
    lawful = P.may_follow(mode)
    if max_len is not None:
        on &= F.col("a.len") + F.col("b.len") <= max_len
    if mode == "simple":  # a closed path is an answer and goes no further
        lawful &= (F.col("a.src") != F.col("a.dst")) | (F.col("a.len") == 0)
    if log is not None and log.detail:
        n = F.count(F.lit(1))
        met, seen = written(a.join(b, on).select(*P.concatenated(), lawful.alias("lawful")), met=n, kept=F.count_if("lawful"))
        log.met[level], log.pruned[level] = seen["met"], seen["met"] - seen["kept"]
        return met.filter("lawful").drop("lawful")
    return a.join(b, on & lawful).select(*P.concatenated())


def _unknown(grown: DataFrame, levels: list[DataFrame]) -> DataFrame:
    """grown without repeats and without the paths of the rounds before."""
    known = reduce(DataFrame.unionByName, levels).select(F.col("src").alias("__src"), F.col("edges").alias("__edges"))
    return grown.dropDuplicates(["src", "edges"]).join(known, (F.col("src") == F.col("__src")) & (F.col("edges") == F.col("__edges")), "left_anti")


def _grow(steps: PathSet, mode: str, seed, max_len: int | None, log: Log) -> PathSet:
    """Each round extends the newest paths only. With steps of one length a path has one decomposition, so rounds
    can't meet; with steps of several, a round's paths are freed of repeats and of those known before."""
    step = _step_side(steps, mode)
    first = _seeded(step, seed)
    if max_len is not None:
        first = first.filter(F.col("len") <= max_len)
    levels, delta, level = [], first, 1
    bound = None if max_len is None else -(-max_len // max(1, steps.facts.least))
    while True:
        last_round = bound is not None and level >= bound
        if last_round and steps.facts.uniform and not log.detail:
            levels.append(delta)  # nothing can follow, so nobody need count it; it reads written tables alone
            log.ended = "bound"
            break
        delta, n = _keep(delta, level, log)
        if level in log.met:
            log.repeated[level] = log.met[level] - log.pruned[level] - n
        if n == 0 and level > 1:
            log.ended = "fixpoint"
            break
        levels.append(delta)
        if last_round or n == 0:
            log.ended = "bound" if n else "fixpoint"
            break
        grown = _extend(delta, step, mode, max_len, log, level + 1)
        delta, level = grown if steps.facts.uniform else _unknown(grown, levels), level + 1
    return PathSet(reduce(DataFrame.unionByName, levels), steps.graph, _facts(steps, max_len))


def between(steps: PathSet, first, last, mode: str = "trail", max_len: int = 6, log: Log | None = None) -> PathSet:
    """Paths from the nodes of `first` to those of `last` by meeting in the middle: paths of at most half the length grow
    from either end and are joined where they meet, so neither side is ever grown to the whole length.

    Steps have one length. A path longer than the forward half is cut there, in one place, so no path is made twice.
    """
    if not steps.facts.uniform:
        raise ValueError("two-sided search is for steps of one length")
    if mode not in ("walk", "trail", "acyclic", "simple"):
        raise ValueError(f"no two-sided search for {mode!r}")
    least = max(1, steps.facts.least)
    rounds = max_len // least
    half = (rounds + 1) // 2
    # inside a closed simple path the halves are acyclic but for its ends; trails and walks are closed under parts
    ahead = recurse(steps, mode, seed=first, max_len=half * least, log=log)
    behind = recurse(steps, mode, seed=last, direction="backward", max_len=(rounds - half) * least, log=log) if rounds > half else None
    ends = _seeded(ahead.df.select(F.col("dst").alias("src"), F.struct(*P.PATH_COLUMNS).alias("path")), last).select("path.*")
    if behind is None:
        return PathSet(ends, steps.graph, _facts(steps, max_len))
    full = ahead.df.filter(F.col("len") == half * least)
    joined = _extend(full, behind.df, mode, max_len)
    return PathSet(ends.unionByName(joined), steps.graph, _facts(steps, max_len))


def _naive(steps: PathSet, mode: str, seed, max_len: int | None, log: Log) -> PathSet:
    """Baseline: each round joins everything found so far with the steps, and stops when the set grows no more."""
    step = _step_side(steps, mode)
    found = _seeded(step, seed)
    if max_len is not None:
        found = found.filter(F.col("len") <= max_len)
    found, n = _keep(found, 1, log)
    level = 1
    while True:
        level += 1
        after, m = _keep(found.unionByName(_extend(found, step, mode, max_len)).dropDuplicates(["src", "edges"]), level, log)
        if m == n:
            log.ended = "fixpoint"
            return PathSet(after, steps.graph, _facts(steps, max_len))
        found, n = after, m


def refuse_cycles(steps: PathSet, seed=None, rounds: int = 100_000) -> None:
    """Raise unless the ends of the steps, as far as the seed reaches, form no cycle.

    Where each node has one way on at most (chains of events, turns or copies), ways are doubled: after k rounds each
    node points 2^k steps on, or has left the graph, so a chain of n steps takes log n rounds. Else nodes without a way
    on, or without a way in, are taken away again and again, from both ends; a rest that stays holds a cycle.
    """
    fault = InfiniteWalkError("walks over a cycle have no bound: give max_len, or a selector that bounds them")
    ends = _kept(steps.endpoints())
    if seed is not None:
        reach = closure(ends, seed).select(F.col("dst").alias("__on")).distinct()
        firsts = _seeded(ends, seed)
        ends = ends.join(reach, F.col("src") == F.col("__on"), "left_semi").union(firsts).distinct()
    ends, n = _keep(ends, 1, Log())
    most = ends.groupBy("src").count().agg(F.max("count")).first()[0] or 0
    if most <= 1:
        for level in range(n.bit_length() + 1):
            if n == 0:
                return
            on = ends.select(F.col("src").alias("__on"), F.col("dst").alias("__to"))
            ends, n = _keep(ends.join(on, F.col("dst") == F.col("__on")).select("src", F.col("__to").alias("dst")), level, Log())
        if n:
            raise fault
        return
    for level in range(rounds):
        if n == 0:
            return
        onward, inward = ends.select(F.col("src").alias("__on")).distinct(), ends.select(F.col("dst").alias("__in")).distinct()
        ends, m = _keep(ends.join(onward, F.col("dst") == F.col("__on"), "left_semi").join(inward, F.col("src") == F.col("__in"), "left_semi"), level, Log())
        if m == n:
            raise fault
        n = m


def closure(ends: DataFrame, seed=None, log: Log | None = None) -> DataFrame:
    """Pairs (src, dst) joined by one or more steps: the classic answer without witness paths.

    Without a seed, the pairs that a hub joins are never searched for or written: one node of each connected part is its
    hub, and every node that reaches it is joined with every node that it reaches. They are made as the result is read.
    What is left are pairs whose ways keep clear of all nodes on a cycle with the hub. Both are found in tasks that hold the
    steps (search.py); round by round, if these are very many or a log of rounds is asked for.
    """
    searched, log = log is None and seed is None, log if log is not None else Log()
    step, seen = written(ends.select("src", "dst").distinct(), n=F.count(F.lit(1)))
    if searched and seen["n"] <= search.HELD:
        return search.closure_of_parts(_kept(search.parts_of(step)))
    if seed is not None:
        return _closed(step, seed, log)
    hubs = _kept(_hubs(step))
    # onward and inward in one recursion, over nodes that know their direction
    way = lambda k, x: F.struct(F.lit(k).alias("way"), F.col(x).alias("id"))
    both = step.select(way(0, "src").alias("src"), way(0, "dst").alias("dst")).union(step.select(way(1, "dst").alias("src"), way(1, "src").alias("dst")))
    reached = _kept(_closed(_kept(both), hubs.select(F.explode(F.array(way(0, "hub"), way(1, "hub")))), log))
    reached = reached.select("src.way", F.col("src.id").alias("src"), F.col("dst.id").alias("dst"))
    own = hubs.select(F.col("hub").alias("src"), F.col("hub").alias("dst"))
    side = lambda k, x: _kept(reached.filter(F.col("way") == k).select("src", "dst").union(own).distinct().select(F.col("src").alias("__hub"), F.col("dst").alias(x)))
    onward, inward = side(0, "__to"), side(1, "__from")
    cyclic = reached.filter("way = 0 AND src = dst").select(F.col("src").alias("__hub"), F.lit(True).alias("__cyclic"))
    spread = max(8, ends.sparkSession.sparkContext.defaultParallelism)
    joined = inward.join(cyclic, "__hub", "left").repartition(spread, "__from").join(onward, "__hub")
    joined = joined.filter("__cyclic OR __from <> __hub OR __to <> __hub").select(F.col("__from").alias("src"), F.col("__to").alias("dst"))
    on = inward.join(onward, (F.col("__from") == F.col("__to")) & (inward["__hub"] == onward["__hub"]), "left_semi").select(F.col("__from").alias("__on"))
    rest = step.join(on, F.col("src") == F.col("__on"), "left_anti").join(on, F.col("dst") == F.col("__on"), "left_anti")
    rest = rest.join(inward.select(F.col("__from").alias("src"), F.lit(True).alias("__in")), "src", "left").join(onward.select(F.col("__to").alias("dst"), F.lit(True).alias("__out")), "dst", "left")
    rest = _kept(rest.select("src", "dst", F.coalesce("__in", F.lit(False)).alias("__in"), F.coalesce("__out", F.lit(False)).alias("__out")))
    return joined.unionByName(_closed(rest, None, log).select("src", "dst"))


def _closed(step: DataFrame, seed, log: Log) -> DataFrame:
    """The closure round by round. Steps may say whether their first node reaches a hub (__in) and their last one is
    reached from one (__out): pairs of both kinds are joined by it and left out, and so is all that follows from them."""
    flags = [c for c in ("__in", "__out") if c in step.columns]
    open_ = (lambda df: df.filter("NOT (__in AND __out)")) if flags else (lambda df: df)
    delta, n = _keep(open_(_seeded(step, seed)), 1, log)
    found, level = delta, 1
    while n:
        level += 1
        met = delta.alias("a").join(step.alias("b"), F.col("a.dst") == F.col("b.src")).select(F.col("a.src"), F.col("b.dst"), *[F.col("a.__in" if c == "__in" else "b.__out") for c in flags])
        known = found.select(F.col("src").alias("__s"), F.col("dst").alias("__t"))
        delta, n = _keep(open_(met).distinct().join(known, (F.col("src") == F.col("__s")) & (F.col("dst") == F.col("__t")), "left_anti"), level, log)
        found = found.union(delta)
    return found


def _hubs(step: DataFrame) -> DataFrame:
    """One node (hub) of each connected part of a graph: that with the most ways through it, and the least of such.
    Parts are found by the least node that any neighbour knows of, which each round looks up again for that node."""
    both = _kept(step.union(step.select("dst", "src")).distinct())
    roots = _kept(both.groupBy("src").agg(F.least("src", F.min("dst")).alias("root")))
    while True:
        near = both.join(roots.select(F.col("src").alias("__n"), "root"), F.col("dst") == F.col("__n")).groupBy("src").agg(F.min("root").alias("__near"))
        least = roots.join(near, "src").select("src", F.col("root").alias("__was"), F.least("root", "__near").alias("__root"))
        jump = roots.select(F.col("src").alias("__n"), F.col("root").alias("__up"))
        roots, seen = written(least.join(jump, F.col("__root") == F.col("__n")).select("src", F.least("__root", "__up").alias("root"), (F.col("__was") > F.least("__root", "__up")).alias("__new")), n=F.count_if("__new"))
        roots = roots.drop("__new")
        if not seen["n"]:
            break
    one = step.groupBy("src").agg(F.count(F.lit(1)).alias("ways_on"))
    two = step.groupBy(F.col("dst").alias("src")).agg(F.count(F.lit(1)).alias("ways_in"))
    ways = roots.join(one, "src").join(two, "src", "left").groupBy("root").agg(F.min(F.struct((-F.col("ways_on") * F.coalesce("ways_in", F.lit(0))).alias("ways"), "src")).alias("best"))
    return ways.select(F.col("best.src").alias("hub"))


def distances(steps: PathSet, seed=None, max_len: int | None = None, log: Log | None = None) -> DataFrame:
    """src, dst, d: least length for every pair, by relaxing pairs that got better until none does. Steps may have
    several lengths, so a pair may get better more than once."""
    log = log if log is not None else Log()
    reach = _kept(steps.df.groupBy("src", "dst").agg(F.min("len").alias("d")))
    known, n = _keep(_seeded(reach, seed), 1, log)
    delta, level = known, 1
    while n:
        level += 1
        grown = delta.alias("a").join(reach.alias("b"), F.col("a.dst") == F.col("b.src")).groupBy(F.col("a.src").alias("src"), F.col("b.dst").alias("dst")).agg(F.min(F.col("a.d") + F.col("b.d")).alias("d"))
        if max_len is not None:
            grown = grown.filter(F.col("d") <= max_len)
        old = known.select(F.col("src").alias("__s"), F.col("dst").alias("__t"), F.col("d").alias("__d"))
        better = grown.join(old, (F.col("src") == F.col("__s")) & (F.col("dst") == F.col("__t")), "left").filter("__d IS NULL OR d < __d").select("src", "dst", "d")
        delta, n = _keep(better, level, log)
        if n:
            known, _ = _keep(known.union(delta).groupBy("src", "dst").agg(F.min("d").alias("d")), level, Log())
    return known if max_len is None else known.filter(F.col("d") <= max_len)


def _shortest(steps: PathSet, seed, max_len: int | None, log: Log) -> PathSet:
    """Steps of one length: a round's paths are shortest where no round before has their ends, so paths grow and pairs
    close in one recursion. Steps of several: distances first, then paths along steps that lose nothing. Either way no
    path is made that is beaten later."""
    step = _step_side(replace(steps, df=least_per_pair(steps.df)), "shortest")
    first, levels, level = _seeded(step, seed), [], 1
    if steps.facts.uniform:
        pairs: list[DataFrame] = []
        bound = None if max_len is None else max_len // max(1, steps.facts.least)
        delta = first if bound != 0 else first.limit(0)
        while True:
            delta, n = _keep(delta, level, log)
            if n or level == 1:
                levels.append(delta)
            if n == 0 or level == bound:
                break
            pairs.append(delta.select(F.col("src").alias("__s"), F.col("dst").alias("__t")).distinct())
            closed = reduce(DataFrame.unionByName, pairs)
            delta = _extend(delta, step, "walk", max_len).join(closed, (F.col("src") == F.col("__s")) & (F.col("dst") == F.col("__t")), "left_anti")
            level += 1
        log.ended = "fixpoint" if n == 0 else "bound"
        return PathSet(reduce(DataFrame.unionByName, levels), steps.graph, _facts(steps, max_len))
    best = distances(steps, seed, max_len, log).select(F.col("src").alias("__s"), F.col("dst").alias("__t"), F.col("d").alias("__d"))
    tight = lambda df: df.join(best, (F.col("src") == F.col("__s")) & (F.col("dst") == F.col("__t")) & (F.col("len") == F.col("__d")), "left_semi")
    delta = tight(first)
    while True:
        delta, n = _keep(delta, level, log)
        if n == 0 and level > 1:
            break
        levels.append(delta)
        if n == 0:
            break
        delta, level = _unknown(tight(_extend(delta, step, "walk", max_len)), levels), level + 1
    log.ended = "fixpoint"
    return PathSet(reduce(DataFrame.unionByName, levels), steps.graph, _facts(steps, max_len))


def _k_best(steps: PathSet, seed, keep: tuple[str, int], max_len: int | None, log: Log) -> PathSet:
    """Walks bounded by pair of ends: the k first by (length, nodes, edges), or all of the k least lengths. The part
    before the last step of a kept walk is kept for its own pair, so each round may drop the rest.

    With steps of one length every round's walks are longer than all before, so only the newest are ranked, behind a
    count for each pair of what it has; with steps of several, all that is known is ranked again.
    """
    how, k = keep
    by = Window.partitionBy("src", "dst")
    out_facts = Facts(steps.facts.least, max_len, True, steps.facts.labels)
    if steps.facts.uniform:
        took = F.count(F.lit(1)) if how == "k_shortest" else F.countDistinct("len")
        delta, levels, counts, level = _seeded(steps.df, seed), [], [], 1
        while True:
            if how == "k_shortest":  # the ranks of the newest, then room for them; the window drops most before its exchange
                delta = delta.withColumn("__r", F.row_number().over(by.orderBy(*P.TIE))).filter(F.col("__r") <= k)
            else:
                delta = delta.withColumn("__r", F.lit(1))
            if counts:
                had = reduce(DataFrame.unionByName, counts).groupBy("__s", "__t").agg(F.sum("__n").alias("__had"))
                delta = delta.join(had, (F.col("src") == F.col("__s")) & (F.col("dst") == F.col("__t")), "left").filter(F.col("__r") + F.coalesce("__had", F.lit(0)) <= k)
            delta, n = _keep(delta.select(*P.PATH_COLUMNS), level, log)
            levels.append(delta)
            if n == 0 or (max_len is not None and (level + 1) * steps.facts.least > max_len):
                break
            counts.append(delta.groupBy(F.col("src").alias("__s"), F.col("dst").alias("__t")).agg(took.alias("__n")))
            delta, level = _extend(delta, steps.df, "walk", max_len), level + 1
        log.ended = "fixpoint" if n == 0 else "bound"
        return PathSet(reduce(DataFrame.unionByName, levels), steps.graph, out_facts)
    rank = F.row_number().over(by.orderBy(*P.TIE)) if how == "k_shortest" else F.dense_rank().over(by.orderBy("len"))
    cut = lambda df: df.withColumn("__r", rank).filter(F.col("__r") <= k).drop("__r")
    found, n = _keep(cut(_seeded(steps.df, seed)).withColumn("__new", F.lit(True)), 1, log)
    level = 1
    while n:
        level += 1
        grown = _extend(found.filter("__new").drop("__new"), steps.df, "walk", max_len).withColumn("__new", F.lit(True))
        both = found.withColumn("__new", F.lit(False)).unionByName(grown)
        both = both.groupBy("src", "edges").agg(*[F.first(c).alias(c) for c in ("dst", "len", "nodes", "elabels")], F.min("__new").alias("__new"))
        found, seen = written(cut(both), n=F.count_if("__new"))
        n = seen["n"]
        log.rounds.append((level, n))
    log.ended = "fixpoint"
    return PathSet(found.select(*P.PATH_COLUMNS), steps.graph, out_facts)


def sql_recursion(spark, edges: DataFrame, mode: str, max_len: int) -> DataFrame:
    """Baseline for small graphs: Spark's own recursive common table expression, in one statement."""
    view = "__path_edges"
    edges.select("src", "dst", "nodes", "edges", "elabels").createOrReplaceTempView(view)
    lawful = {"walk": "true", "trail": "NOT array_contains(p.edges, e.edges[0])", "acyclic": "NOT array_contains(p.nodes, e.dst)"}[mode]
    base = "src <> dst" if mode == "acyclic" else "true"
    return spark.sql(f"""
WITH RECURSIVE grown(src, dst, len, nodes, edges, elabels) MAX RECURSION LEVEL {max_len + 1} AS (
  SELECT src, dst, 1, nodes, edges, elabels FROM {view} WHERE {base}
  UNION ALL
  SELECT p.src, e.dst, p.len + 1, array_append(p.nodes, e.dst), concat(p.edges, e.edges), concat(p.elabels, e.elabels)
  FROM grown p JOIN {view} e ON p.dst = e.src WHERE p.len < {max_len} AND {lawful})
SELECT * FROM grown""")
