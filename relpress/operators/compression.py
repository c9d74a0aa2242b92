"""Compressed relations: building entries, the area-cover compressor and the compressors it is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.itemsets import as_items, mask_of, value_at
from ..model import CompressedRelation, Relation
from ..plans.staging import staged
from . import mining, selection

#: Candidates from which dense covers are bit vectors; fewer are quick either way.
DENSE_SETS = 1000


def build(rel: Relation, tuples: DataFrame, sets: DataFrame, chosen: DataFrame, n_mined: int | None = None, threshold: int | None = None) -> CompressedRelation:
    """Entries from the chosen (rank, tid, head), numbered by their rank; uncovered tuples go to the default table."""
    chosen = staged(chosen, "chosen")
    size = chosen.groupBy("rank").agg(F.count("*").alias("freq"))
    heads = staged(sets.drop("freq").join(size, "rank").select(F.col("rank").alias("entry"), "items", "len", "freq"), "heads")
    # A chosen tuple brings its head along, so no join meets the many rows of one entry.
    rows = tuples.join(chosen.select("tid", F.col("rank").alias("entry"), mask_of(F.col("head")).alias("mask")), "tid")
    body = rows.select("entry", "tid", F.filter("items", lambda x: F.getbit("mask", x["p"]) == 0).alias("items"))
    return CompressedRelation(rel.scope, heads, body, tuples.join(chosen, "tid", "left_anti").select("tid", "items"), n_mined, threshold)


def entry(rel: Relation, fixed: dict[str, int]) -> DataFrame:
    """The residual table of a single itemset: tuples with these values, less these columns."""
    d = rel.df
    for c, v in fixed.items():
        d = d.where(F.col(c) == v)
    return d.drop(*fixed)


def choose(rel: Relation, sets: DataFrame, objective: str, overlap: str = "drop", n_mined: int | None = None, threshold: int | None = None) -> CompressedRelation:
    """Greedy choice among candidate ``sets`` and the compressed relation that follows."""
    tuples = rel.numbered()
    ranked = selection.rank(sets, rel.arity, objective)
    # A cover's row takes more than 64 bits: where covers hold more than one tuple in 64, bit vectors are the smaller form.
    n, covered = ranked.agg(F.count("*"), F.sum("freq")).first()
    if overlap == "drop" and 64 * (covered or 0) > n * tuples.count() and n >= DENSE_SETS:
        chosen, _ = selection.greedy_bits(ranked, tuples)
    else:
        chosen, _ = selection.greedy(ranked, selection.cover(ranked, tuples), overlap, rel.arity, objective)
    return build(rel, tuples, ranked, chosen, n_mined, threshold)


def candidates(rel: Relation, s_min: int, kind: str = "maximal") -> DataFrame:
    """Frequent, closed or maximal sets of at least two tuples, by the engine that suits the width."""
    if kind == "frequent":
        return mining.frequent(rel, s_min) if rel.arity <= mining.CUBE_TAKEN else mining.frequent_levelwise(rel, s_min)
    if rel.arity <= mining.CUBE_TAKEN:
        sets = mining.frequent(rel, s_min)
        return mining.closed(sets) if kind == "closed" else mining.maximal(sets)
    return mining.closed_shards(rel, s_min) if kind == "closed" else mining.maximal_shards(rel, s_min)


def support_threshold(rel: Relation, k: float | int, reduce: str = "mean") -> int:
    """The threshold from the k most frequent closed sets (k a count, or a share of the tuples), mined best first."""
    most = mining.count_of(k, rel.df.count())
    if most <= 0:
        return 2
    sets = staged(mining.top_closed_shards(rel, most), "closed")
    return mining.threshold(sets, most, reduce)


def area_cover(rel: Relation, k: float | int = 0.4, reduce: str = "mean", overlap: str = "drop", s_min: int | None = None, kind: str = "maximal", objective: str = "area") -> CompressedRelation:
    """The area-cover compressor: threshold, maximal sets, choice by area with disjoint covers, materialisation.

    A given ``s_min`` replaces the automatic threshold; ``kind`` and ``objective`` are for comparison.
    """
    # The relation is read by every step: written once, so that its query does not run again.
    rel = Relation(staged(rel.df, "relation"), rel.scope, rel.name, rel.sign)
    s_min = s_min or support_threshold(rel, k, reduce)
    sets = staged(candidates(rel, s_min, kind), "candidates")
    return choose(rel, sets, objective, overlap, sets.count(), s_min)


def tiles(rel: Relation, k: int, s_min: int = 2) -> DataFrame:
    """The first k itemsets of the greedy choice by area: a stand-in for the k disjoint tiles of largest area, which are hard to find."""
    c = area_cover(rel, s_min=s_min)
    return mining.top(c.heads, k, F.col("len") * F.col("freq")).select("items", "len", "freq")


def paths(rel: Relation, s_min: int = 2) -> DataFrame:
    """Root-to-node paths of the frequency-ordered prefix tree, as itemsets; the tree is the table of prefix counts."""
    items = mining.frequent_items(rel, 1)
    each = rel.df.select(*rel.scope, F.explode(as_items(rel.scope)).alias("x")).join(items, (F.col("x.p") == F.col("p")) & (F.col("x.v") == F.col("v")))
    ordered = each.groupBy(*rel.scope).agg(F.sort_array(F.collect_list(F.struct((-F.col("freq")).alias("f"), "p", "v"))).alias("s"))
    prefix = F.explode(F.transform(F.sequence(F.lit(1), F.lit(max(1, rel.arity - 1))), lambda n: F.slice("s", 1, n)))
    counted = ordered.select(prefix.alias("s")).groupBy("s").agg(F.count("*").alias("freq")).where(F.col("freq") >= s_min)
    return counted.select(F.array_sort(F.transform("s", lambda x: F.struct(x["p"].alias("p"), x["v"].alias("v")))).alias("items"), F.size("s").alias("len"), "freq")


def slices(rel: Relation, s_min: int = 2, candidates_: str = "paths", objective: str = "savings") -> CompressedRelation:
    """The itemset baselines: 'savings' on paths is the savings-slice compressor, 'rate' the rate-tree; 'all' takes every frequent set."""
    sets = staged(paths(rel, s_min) if candidates_ == "paths" else candidates(rel, s_min, "frequent"), "slices")
    return choose(rel, sets, objective, "drop", sets.count(), s_min)


def savings_slice(rel: Relation, s_min: int = 2, candidates_: str = "paths") -> CompressedRelation:
    return slices(rel, s_min, candidates_, "savings")


def rate_tree(rel: Relation, s_min: int = 2, candidates_: str = "paths") -> CompressedRelation:
    return slices(rel, s_min, candidates_, "rate")


def cartesian(rel: Relation, order: list[str] | None = None) -> DataFrame:
    """Products of value sets: columns in turn merge rows that differ in this column only. Columns are sorted arrays."""
    d = rel.df.select(*[F.array(F.col(c).cast("int")).alias(c) for c in rel.scope])
    for c in order or rel.scope[::-1]:
        rest = [x for x in rel.scope if x != c]
        d = d.groupBy(*rest).agg(F.sort_array(F.flatten(F.collect_list(c))).alias(c)) if rest else d.agg(F.sort_array(F.flatten(F.collect_list(c))).alias(c))
    return d.select(*rel.scope)


def wildcard(rel: Relation, domains: DataFrame | None = None, order: list[str] | None = None) -> DataFrame:
    """Short supports: product rows where a column that holds its whole domain becomes "any" (null, its bit in ``any``),
    and other columns are single values again."""
    domains = domains if domains is not None else rel.domains()
    size = {r["var"]: r["n"] for r in domains.groupBy("var").agg(F.count("*").alias("n")).collect()}
    d = rel.df.select(*[F.array(F.col(c).cast("int")).alias(c) for c in rel.scope], F.lit(0).cast("bigint").alias("any"))
    for c in order or rel.scope[::-1]:
        i, rest = rel.scope.index(c), [x for x in rel.scope if x != c]
        d = d.groupBy(*rest, "any").agg(F.sort_array(F.flatten(F.collect_list(c))).alias(c))
        full = F.size(c) == size.get(i, -1)
        d = d.withColumn(c, F.explode(F.when(full, F.array(F.array().cast("array<int>"))).otherwise(F.transform(c, lambda v: F.array(v))))).withColumn("any", F.when(F.size(c) == 0, F.col("any") + (1 << i)).otherwise(F.col("any")))
    return d.select(*[F.get(c, F.lit(0)).alias(c) for c in rel.scope], "any")


def restricted(rel: Relation, order: list[str] | None = None) -> DataFrame:
    """Rows with simple conditions: product rows whose value sets are given as lo, hi and whether every code between is in."""
    d = cartesian(rel, order)
    return d.select(*[F.struct(F.array_min(c).alias("lo"), F.array_max(c).alias("hi"), (F.size(c) == F.array_max(c) - F.array_min(c) + 1).alias("dense"), F.col(c).alias("set")).alias(c) for c in rel.scope])


def smart(rel: Relation, s_min: int = 2) -> tuple[DataFrame, DataFrame]:
    """Rows with conditions between columns, and the tuples (tid, items) that no row takes.

    A row (x, y, op, items, freq) stands for the tuples with ``items`` at the other columns and, at columns x and y, all pairs
    of values of the two domains for which the comparison ``op`` ('=', '<', '>') holds. Rows are chosen by size, disjoint.
    """
    tuples = rel.numbered()
    domains = staged(rel.domains().select("var", "code"), "domains")
    parts = []
    for x in range(rel.arity):
        for y in range(x + 1, rel.arity):
            others = F.filter("items", lambda i: (i["p"] != x) & (i["p"] != y))
            d = tuples.select("tid", F.lit(x).alias("x"), F.lit(y).alias("y"), others.alias("items"), value_at(F.col("items"), x).alias("a"), value_at(F.col("items"), y).alias("b"))
            parts.append(d.withColumn("op", F.when(F.col("a") == F.col("b"), "=").when(F.col("a") < F.col("b"), "<").otherwise(">")))
    each = parts[0]
    for p in parts[1:]:
        each = each.unionByName(p)
    # How many pairs of two finite domains fit each comparison.
    two = domains.select(F.col("var").alias("x"), F.col("code").alias("a")).join(domains.select(F.col("var").alias("y"), F.col("code").alias("b")), F.col("x") < F.col("y"))
    whole = two.withColumn("op", F.when(F.col("a") == F.col("b"), "=").when(F.col("a") < F.col("b"), "<").otherwise(">")).groupBy("x", "y", "op").agg(F.count("*").alias("pairs"))
    each = staged(each.drop("a", "b"), "pairs")
    found = each.groupBy("x", "y", "op", "items").agg(F.count("*").alias("freq")).join(whole, ["x", "y", "op"]).where((F.col("freq") == F.col("pairs")) & (F.col("freq") >= s_min)).drop("pairs")
    sets = found.withColumns({"len": F.size("items"), "score": F.col("freq").cast("double")}).orderBy(F.desc("freq"), "x", "y", "op", "items")
    sets = staged(sets.withColumn("rank", F.monotonically_increasing_id()), "smart")
    covers = each.join(sets.select("x", "y", "op", "items", "rank"), ["x", "y", "op", "items"]).select("rank", "tid")
    chosen, _ = selection.greedy(sets, covers)
    rows = sets.join(chosen.select("rank").distinct(), "rank", "left_semi").select("x", "y", "op", "items", "freq")
    return rows, tuples.join(chosen.select("tid"), "tid", "left_anti")


def segmented(c: CompressedRelation, most: int = 1000) -> DataFrame:
    """Rows of segments (entry, part, items, rows): a head and a table of what goes with it, nested.

    An entry of more than ``most`` tuples is several segments with the same head, so that no row holds an unbounded table; a
    default tuple is a segment of its own.
    """
    numbered = c.body.withColumn("part", F.floor((F.row_number().over(Window.partitionBy("entry").orderBy("tid")) - 1) / most).cast("int"))
    rest = numbered.groupBy("entry", "part").agg(F.sort_array(F.collect_list("items")).alias("rows"))
    alone = c.default.select(F.lit(-1).cast("bigint").alias("entry"), F.lit(0).alias("part"), F.array().cast(c.heads.schema["items"].dataType).alias("items"), F.array("items").alias("rows"))
    return rest.join(c.heads.select("entry", "items"), "entry").select("entry", "part", "items", "rows").unionByName(alone)


def microstructure(rel: Relation, s_min: int = 2) -> CompressedRelation:
    """Groups from the graph of values that occur together: an edge is a pair of values with the number of tuples that hold
    both. A tuple joins the group of its heaviest edge, grown by the values that all tuples of the group share; groups are
    entries as far as their covers do not overlap.
    """
    tuples = rel.df.select(as_items(rel.scope).alias("t")).withColumn("row", F.monotonically_increasing_id())
    rows = staged(tuples.select("row", "t"), "rows")
    pair = F.explode(F.flatten(F.transform("t", lambda x: F.transform(F.filter("t", lambda y: y["p"] > x["p"]), lambda y: F.array(x, y)))))
    edges = rows.select("row", "t", pair.alias("edge"))
    weight = staged(edges.groupBy("edge").agg(F.count("*").alias("w")), "edges")
    heaviest = edges.join(weight, "edge").groupBy("row").agg(F.min(F.struct((-F.col("w")).alias("w"), "edge")).alias("best"), F.first("t").alias("t"))
    held = staged(heaviest.select(F.col("best.edge").alias("edge"), "t"), "groups")
    size = held.groupBy("edge").agg(F.count("*").alias("n")).where(F.col("n") >= s_min)
    shared = held.select("edge", F.explode("t").alias("x")).groupBy("edge", "x").agg(F.count("*").alias("m")).join(size, "edge").where("m = n")
    groups = shared.groupBy("edge").agg(F.array_sort(F.collect_list("x")).alias("items")).select("items").distinct()  # a tuple's items at most
    # Frequencies over all tuples, as a group's values may stand elsewhere too.
    ranked = staged(groups.withColumns({"rank": F.monotonically_increasing_id(), "len": F.size("items")}), "grown")
    covered = selection.cover(ranked, rows.select(F.col("row").alias("tid"), F.col("t").alias("items"))).groupBy("rank").agg(F.count("*").alias("freq"))
    sets = staged(ranked.join(covered, "rank").where(F.col("freq") >= s_min).select("items", "len", "freq"), "sets")
    return choose(rel, sets, "savings", "drop", sets.count(), s_min)


def diagram(rel: Relation, order: list[str] | None = None, automaton: bool = False) -> DataFrame:
    """Decision diagram edges (level, node, code, child): equal suffix sets share a node; the sink is 0, the root level 0.

    From the last column up, prefixes with equal sets of (code, child) share a node, which is numbered within its level: by
    the least prefix that leads to it. ``automaton`` numbers the distinct sets of all levels, so that equal states of any
    levels are one state.
    """
    cols = order or rel.scope
    d = rel.df.select(*[F.col(c).cast("int").alias(c) for c in cols], F.lit(0).cast("bigint").alias("child"))
    edges, states, last = [], None, 0
    for level in range(len(cols) - 1, -1, -1):
        c = cols[level]
        out = F.sort_array(F.collect_set(F.struct(F.col(c).alias("code"), "child")))
        d = d.groupBy(*cols[:level]).agg(out.alias("out")) if level else d.agg(out.alias("out")).where(F.size("out") > 0)
        d = staged(d, f"level{level}")
        # Nodes are told apart by their sets themselves and numbered within ranges of these, on from those below.
        new = d.select("out").distinct()
        new = new.join(states, "out", "left_anti") if automaton and states is not None else new
        new = staged(new.withColumn("node", F.monotonically_increasing_id() + last + 1), f"nodes{level}")
        last = max(last, new.agg(F.max("node")).first()[0] or 0)
        known = new if not automaton or states is None else states.unionByName(new)
        states = known if automaton else None
        d = d.join(known, "out")
        edges.append(d.select(F.lit(level).alias("level"), "node", "out").distinct().select("level", "node", F.explode("out").alias("e")).select("level", "node", "e.code", "e.child"))
        d = d.select(*cols[:level], F.col("node").alias("child"))
    found = edges[0]
    for e in edges[1:]:
        found = found.unionByName(e)
    return found


def bitset(tuples: DataFrame) -> DataFrame:
    """(var, code, bucket, bits): bitmaps over tuple numbers, 32 768 to a bucket; numbers are made dense within sort order."""
    # A bucket starts at 1, so numbers from 0 on are moved by one.
    x = tuples.select((F.col("tid") + 1).alias("tid"), F.explode("items").alias("x"))
    return x.groupBy(F.col("x.p").alias("var"), F.col("x.v").alias("code"), F.bitmap_bucket_number("tid").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("tid")).alias("bits"))


def dense(rel: Relation) -> DataFrame:
    """(tid, items) with dense numbers: ranks within range partitions plus the counts of the partitions before."""
    part = staged(rel.df.repartitionByRange(*rel.scope).withColumn("_p", F.spark_partition_id()), "parts")
    counts = part.groupBy("_p").agg(F.count("*").alias("n"))
    offset = counts.select("_p", (F.sum("n").over(Window.orderBy("_p")) - F.col("n")).alias("before"))
    numbered = part.withColumn("r", F.row_number().over(Window.partitionBy("_p").orderBy(*rel.scope))).join(F.broadcast(offset), "_p")
    return numbered.select((F.col("before") + F.col("r") - 1).cast("bigint").alias("tid"), as_items(rel.scope).alias("items"))
