"""Arc-consistency filters of one constraint: which live values have a valid tuple.

All give the same result and differ in the state they keep and the cells they look at. ``domains`` is (var, code) of the
live values by position; a result is (var, code) of the supported live values. Domains of up to ``DOMAIN_VALUES`` values
together go into a predicate; beyond, every filter joins its rows with the table of live values instead.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.itemsets import as_items
from ..model import CompressedRelation, Relation
from ..plans.staging import staged

#: Live values of all positions together up to which they go into a predicate.
DOMAIN_VALUES = 50_000


def live_values(domains: DataFrame, arity: int) -> list[list[int]] | None:
    """Codes by position, or None if there are too many for a predicate."""
    rows = domains.select("var", "code").distinct().limit(DOMAIN_VALUES + 1).collect()
    if len(rows) > DOMAIN_VALUES:
        return None
    out: list[list[int]] = [[] for _ in range(arity)]
    for r in rows:
        out[r["var"]].append(r["code"])
    return [sorted(x) for x in out]


def _valid(items: Column, live: list[list[int]], only: list[int] | None = None) -> Column:
    """Whether all values of an itemset (at positions ``only``) are live."""

    def holds(p: int) -> Column:
        return F.forall(items, lambda x: (x["p"] != p) | x["v"].isin(live[p]) if live[p] else (x["p"] != p))

    return reduce(lambda a, b: a & b, [holds(p) for p in (range(len(live)) if only is None else only)], F.lit(True))


def values_of(rows: DataFrame) -> DataFrame:
    """(var, code) of the items in ``rows``."""
    return rows.select(F.explode("items").alias("x")).select(F.col("x.p").alias("var"), F.col("x.v").alias("code")).distinct()


def valid_rows(rows: DataFrame, domains: DataFrame, arity: int, only: list[int] | None = None, key: str = "tid") -> DataFrame:
    """The rows (named by ``key``) all of whose values, at positions ``only``, are live."""
    live = live_values(domains, arity)
    if live is not None:
        return rows.where(_valid(F.col("items"), live, only))
    return rows.join(_dead(rows, domains, only, key), key, "left_anti")


def _dead(rows: DataFrame, domains: DataFrame, only: list[int] | None, key: str) -> DataFrame:
    """Names of the rows with a value that is not live, by a join."""
    x = rows.select(key, F.explode("items").alias("x")).select(key, F.col("x.p").alias("var"), F.col("x.v").alias("code"))
    x = x if only is None else x.where(F.col("var").isin(only))
    return x.join(domains.select("var", "code"), ["var", "code"], "left_anti").select(key).distinct()


def _met(rows: DataFrame, scope: list[str], domains: DataFrame, sets: list[Column], free: list[Column] | None = None) -> DataFrame:
    """What rows of value sets support, by joins: each column must meet its live values, or be ``free`` with some live."""
    rows = staged(rows.withColumn("_row", F.monotonically_increasing_id()), "numbered")
    free = free or [F.lit(False)] * len(scope)
    some = _stacked([rows.select("_row", F.lit(i).alias("var"), F.explode(s).alias("code")) for i, s in enumerate(sets)])
    hit = staged(some.join(domains.select("var", "code"), ["var", "code"], "left_semi"), "met")
    whole = rows.select("_row", F.explode(F.filter(F.array(*[F.when(f, F.lit(i)) for i, f in enumerate(free)]), lambda x: x.isNotNull())).alias("var"))
    whole = whole.join(domains.select("var").distinct(), "var", "left_semi")
    columns = hit.select("_row", "var").distinct().unionByName(whole.select("_row", "var"))
    alive = staged(columns.groupBy("_row").agg(F.count("*").alias("n")).where(F.col("n") == len(scope)).select("_row"), "alive")
    open_ = whole.join(alive, "_row", "left_semi").select("var").distinct()
    return _stacked([hit.join(alive, "_row", "left_semi").select("var", "code"), domains.select("var", "code").join(open_, "var", "left_semi")])


def scan(tuples: DataFrame, domains: DataFrame, arity: int) -> DataFrame:
    """Simple tabular reduction: test every column of every tuple, keep the values of the valid ones."""
    return values_of(valid_rows(tuples, domains, arity))


def settled(tuples: DataFrame, domains: DataFrame, arity: int, changed: list[int]) -> DataFrame:
    """Tabular reduction that tests only changed columns, and seeks supports only where more than one value is live.

    Tuples must be valid on the unchanged columns, as they are after the call before.
    """
    rows = valid_rows(tuples, domains, arity, changed)
    bound = [r["var"] for r in domains.groupBy("var").agg(F.count_distinct("code").alias("n")).where("n = 1").collect()]  # positions
    seek = rows.select(F.filter("items", lambda x: ~x["p"].isin(bound)).alias("items")) if bound else rows
    found = values_of(seek)
    if bound:
        alive = rows.limit(1).select(F.lit(1).alias("one"))
        found = found.unionByName(domains.where(F.col("var").isin(bound)).select("var", "code").join(alive, F.lit(True), "left_semi"))
    return found


def residues(tuples: DataFrame, domains: DataFrame, arity: int, last: DataFrame) -> DataFrame:
    """Supports with residues: values whose last support (var, code, tid) is still valid are done; the rest are sought."""
    rows = valid_rows(tuples, domains, arity)
    held = last.join(rows.select("tid"), "tid", "left_semi").join(domains, ["var", "code"], "left_semi").select("var", "code")
    rest = domains.select("var", "code").join(held, ["var", "code"], "left_anti")
    return held.unionByName(values_of(rows).join(rest, ["var", "code"], "left_semi")).distinct()


def residues_of(tuples: DataFrame) -> DataFrame:
    """(var, code, tid): a first support of every value."""
    return tuples.select("tid", F.explode("items").alias("x")).groupBy(F.col("x.p").alias("var"), F.col("x.v").alias("code")).agg(F.min("tid").alias("tid"))


def dual(tuples: DataFrame, removed: DataFrame) -> DataFrame:
    """Value lists: tuples in the lists of removed values (var, code) die, a value without a live tuple goes."""
    x = tuples.select("tid", F.explode("items").alias("x")).select("tid", F.col("x.p").alias("var"), F.col("x.v").alias("code"))
    dead = x.join(removed, ["var", "code"], "left_semi").select("tid").distinct()
    return x.join(dead, "tid", "left_anti").select("var", "code").distinct()


def counters(tuples: DataFrame, removed: DataFrame, reset: str = "never") -> DataFrame:
    """Support counters per value, less those of dying tuples; 'auto' counts the survivors anew where they are fewer."""
    x = tuples.select("tid", F.explode("items").alias("x")).select("tid", F.col("x.p").alias("var"), F.col("x.v").alias("code"))
    dead = x.join(removed, ["var", "code"], "left_semi").select("tid").distinct()
    if reset == "auto" and 2 * dead.count() > tuples.count():
        return x.join(dead, "tid", "left_anti").groupBy("var", "code").agg(F.count("*").alias("n")).select("var", "code")
    held = x.groupBy("var", "code").agg(F.count("*").alias("n"))
    gone = x.join(dead, "tid", "left_semi").groupBy("var", "code").agg(F.count("*").alias("g"))
    return held.join(gone, ["var", "code"], "left").where(F.col("n") - F.coalesce("g", F.lit(0)) > 0).select("var", "code")


def entries(c: CompressedRelation, domains: DataFrame) -> tuple[DataFrame, DataFrame]:
    """On the compressed form: heads first, bodies of live heads only. (supported values, live rows by entry).

    Live rows are (entry, live, rows): an entry with none is dead; the default table is entry -1.
    """
    heads = valid_rows(c.heads, domains, c.arity, key="entry")
    body = valid_rows(c.body.join(heads.select("entry"), "entry", "left_semi"), domains, c.arity)
    default = valid_rows(c.default, domains, c.arity)
    count = body.groupBy("entry").agg(F.count("*").alias("live"))
    alive = heads.join(count.select("entry"), "entry", "left_semi")
    found = values_of(alive).unionByName(values_of(body)).unionByName(values_of(default)).distinct()
    state = c.heads.select("entry", F.col("freq").alias("rows")).join(count, "entry", "left").select("entry", F.coalesce("live", F.lit(0)).alias("live"), "rows")
    rest = default.agg(F.count("*").alias("live")).crossJoin(c.default.agg(F.count("*").alias("rows")))  # one row each
    return found, state.unionByName(rest.select(F.lit(-1).cast("bigint").alias("entry"), "live", "rows"))


def mark(rows: DataFrame, domains: DataFrame, arity: int, depth: int) -> DataFrame:
    """Rows (with ``dead_at``, null for live) after a filter call at a search depth: invalid live rows die there."""
    live = live_values(domains, arity)
    if live is None:
        dead = _dead(rows.where("dead_at IS NULL"), domains, None, "tid").select("tid", F.lit(depth).alias("_now"))
        return rows.join(dead, "tid", "left").withColumn("dead_at", F.coalesce("dead_at", "_now")).select(*rows.columns)
    dies = ~_valid(F.col("items"), live)
    return rows.withColumn("dead_at", F.when(F.col("dead_at").isNull() & dies, F.lit(depth)).otherwise(F.col("dead_at")))


def restore(rows: DataFrame, depth: int) -> DataFrame:
    """Back to a lower depth: rows that died deeper live again; nothing is moved."""
    return rows.withColumn("dead_at", F.when(F.col("dead_at") <= depth, F.col("dead_at")))


def cartesian(products: DataFrame, scope: list[str], domains: DataFrame) -> DataFrame:
    """On product rows (arrays of values): a row is valid if every set meets the live domain, and supports what it meets."""
    live = live_values(domains, len(scope))
    if live is None:
        return _met(products, scope, domains, [F.col(c) for c in scope])
    sets = [F.array_intersect(F.col(c), F.array(*[F.lit(v) for v in live[i]]).cast("array<int>")) for i, c in enumerate(scope)]
    rows = products.select(*[s.alias(c) for s, c in zip(sets, scope)]).where(reduce(lambda a, b: a & b, [F.size(c) > 0 for c in scope]))
    return _stacked([rows.select(F.lit(i).alias("var"), F.explode(c).alias("code")) for i, c in enumerate(scope)])


def wildcard(rows: DataFrame, scope: list[str], domains: DataFrame) -> DataFrame:
    """On rows with "any": such a column passes, and supports its whole live domain."""
    live = live_values(domains, len(scope))
    if live is None:
        bits = [F.getbit(F.col("any"), F.lit(i)) == 1 for i in range(len(scope))]
        return _met(rows, scope, domains, [F.when(~f, F.array(F.col(c))) for f, c in zip(bits, scope)], bits)
    free = [F.getbit(F.col("any"), F.lit(i)) == 1 for i in range(len(scope))]
    ok = reduce(lambda a, b: a & b, [F.when(f, F.lit(bool(live[i]))).otherwise(F.col(c).isin(live[i]) if live[i] else F.lit(False)) for i, (f, c) in enumerate(zip(free, scope))])
    valid = rows.where(ok)
    some = [valid.where(~f).select(F.lit(i).alias("var"), F.col(c).alias("code")) for i, (f, c) in enumerate(zip(free, scope))]
    whole = valid.agg(*[F.max(f).alias(f"w{i}") for i, f in enumerate(free)]).select(F.explode(F.filter(F.array(*[F.when(F.col(f"w{i}"), F.lit(i)) for i in range(len(scope))]), lambda x: x.isNotNull())).alias("var"))
    return _stacked([*some, domains.select("var", "code").join(whole, "var", "left_semi")])


def restricted(rows: DataFrame, scope: list[str], domains: DataFrame) -> DataFrame:
    """On rows of ranges: a dense range is tested by its ends, another by its set."""
    live = live_values(domains, len(scope))
    if live is None:
        return _met(rows, scope, domains, [F.col(f"{c}.set") for c in scope])

    def part(i: int, c: str) -> Column:
        values = F.array(*[F.lit(v) for v in live[i]]).cast("array<int>")
        inside = F.filter(values, lambda v: (v >= F.col(f"{c}.lo")) & (v <= F.col(f"{c}.hi")))
        return F.when(F.col(f"{c}.dense"), inside).otherwise(F.array_intersect(F.col(f"{c}.set"), values)).alias(c)

    met = rows.select(*[part(i, c) for i, c in enumerate(scope)]).where(reduce(lambda a, b: a & b, [F.size(c) > 0 for c in scope]))
    return _stacked([met.select(F.lit(i).alias("var"), F.explode(c).alias("code")) for i, c in enumerate(scope)])


def smart(rows: DataFrame, rest: DataFrame, domains: DataFrame, arity: int) -> DataFrame:
    """On rows with comparisons: a row is valid if its items are live and some pair of live values fits its comparison."""
    live = domains.select("var", "code").distinct()
    ok = valid_rows(staged(rows.withColumn("tid", F.monotonically_increasing_id()), "rows"), live, arity)
    kinds = ok.select("x", "y", "op").distinct()
    a, b = live.select(F.col("var").alias("x"), F.col("code").alias("a")), live.select(F.col("var").alias("y"), F.col("code").alias("b"))
    met = staged(kinds.join(a, "x").join(b, "y").where("CASE op WHEN '=' THEN a = b WHEN '<' THEN a < b ELSE a > b END"), "met")  # finite domains
    alive = ok.join(met, ["x", "y", "op"], "left_semi")
    sides = met.select(F.col("x").alias("var"), F.col("a").alias("code")).unionByName(met.select(F.col("y").alias("var"), F.col("b").alias("code")))
    return _stacked([values_of(alive), sides, scan(rest, live, arity)])


def bitset_rows(rows: DataFrame, scope: list[str], domains: DataFrame) -> DataFrame:
    """Bit vectors over short rows (a column marked "any" has its bit with every value) or product rows (arrays)."""
    rows = staged(rows.withColumn("tid", F.monotonically_increasing_id()), "rows")
    short = "any" in rows.columns
    every = domains.groupBy("var").agg(F.collect_set("code").alias("codes"))  # finite domains
    parts = []
    for i, c in enumerate(scope):
        if short:
            free = F.getbit(F.col("any"), F.lit(i)) == 1
            parts.append(rows.where(~free).select("tid", F.lit(i).alias("var"), F.col(c).alias("code")))
            parts.append(rows.where(free).select("tid", F.lit(i).alias("var")).join(every.where(F.col("var") == i), "var").select("tid", "var", F.explode("codes").alias("code")))
        else:
            parts.append(rows.select("tid", F.lit(i).alias("var"), F.explode(c).alias("code")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    tuples = out.groupBy("var", "code", F.bitmap_bucket_number(F.col("tid") + 1).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("tid") + 1)).alias("bits"))
    return bitset(tuples, domains, len(scope))


def diagram_edges(edges: DataFrame, arity: int, domains: DataFrame) -> DataFrame:
    """The edges of live values between nodes reached from the root and nodes that reach the sink."""
    # Each level is read on the way down and on the way up: written, so that plans do not nest level in level.
    edges = staged(edges, "edges")
    e = edges.join(domains.select(F.col("var").alias("level"), "code"), ["level", "code"], "left_semi")
    top = edges.where("level = 0").select("node").distinct()
    down = []
    for level in range(arity):
        here = staged(e.where(F.col("level") == level).join(top, "node", "left_semi").select("level", "node", "code", "child"), f"down{level}")
        down.append(here)
        top = here.select(F.col("child").alias("node")).distinct()
    good, kept = staged(top, "sink"), []
    for level in range(arity - 1, -1, -1):
        here = staged(down[level].join(good.withColumnRenamed("node", "child"), "child", "left_semi").select("level", "node", "code", "child"), f"up{level}")
        kept.append(here)
        good = here.select("node").distinct()
    out = kept[0]
    for k in kept[1:]:
        out = out.unionByName(k)
    return out


def diagram(edges: DataFrame, arity: int, domains: DataFrame) -> DataFrame:
    """On a decision diagram: the values of the edges that stay."""
    return diagram_edges(edges, arity, domains).select(F.col("level").alias("var"), "code").distinct()


def bitset(bits: DataFrame, domains: DataFrame, arity: int, changed: list[int] | None = None, mode: str = "current") -> DataFrame:
    """On bitmaps (var, code, bucket, bits): the table's bitmap is the conjunction over columns of the disjunction of live
    values; a value is supported where its bitmap meets it.

    'current' keeps the buckets of the table that still hold a bit and tests changed columns only; 'lists' works on all.
    """
    live = bits.join(domains, ["var", "code"], "left_semi")
    test = live if changed is None or mode == "lists" else live.where(F.col("var").isin(changed))
    need = arity if changed is None or mode == "lists" else len(changed)
    each = test.groupBy("bucket", "var").agg(F.bitmap_or_agg("bits").alias("bits"))
    table = each.groupBy("bucket").agg(F.bitmap_and_agg("bits").alias("table"), F.count("*").alias("n")).where(F.col("n") == need)
    if mode == "current":
        table = table.where(F.bitmap_count("table") > 0)
    met = live.join(table.select("bucket", "table"), "bucket")
    both = met.select("var", "code", "bucket", F.explode(F.array("bits", "table")).alias("b")).groupBy("var", "code", "bucket").agg(F.bitmap_and_agg("b").alias("b"))
    return both.where(F.bitmap_count("b") > 0).select("var", "code").distinct()


def work(c: CompressedRelation, domains: DataFrame) -> DataFrame:
    """Cells a filter call looks at, on the flat table and on the compressed form (a proxy for its time)."""
    heads = c.heads.select(F.sum("len").alias("h")).select(F.coalesce("h", F.lit(0)).alias("h"))
    body = c.body.join(valid_rows(c.heads, domains, c.arity, key="entry").select("entry"), "entry", "left_semi").select(F.coalesce(F.sum(F.size("items")), F.lit(0)).alias("b"))
    rest = c.default.select((F.count("*") * c.arity).alias("d"))
    flat = c.body.select((F.count("*") * c.arity).alias("f"))
    return heads.crossJoin(body).crossJoin(rest).crossJoin(flat).select((F.col("f") + F.col("d")).cast("bigint").alias("flat_cells"), (F.col("h") + F.col("b") + F.col("d")).cast("bigint").alias("entry_cells"))  # one row each


def _stacked(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.distinct()


def first_supports(rel: Relation) -> DataFrame:
    """(var, code, n): how many tuples support each value."""
    return rel.df.select(F.explode(as_items(rel.scope)).alias("x")).groupBy(F.col("x.p").alias("var"), F.col("x.v").alias("code")).agg(F.count("*").alias("n"))


def restrict(domains: DataFrame, removed: dict[int, list[int]]) -> DataFrame:
    """Live values left after removing some."""
    d = domains.select("var", "code")
    for var, codes in removed.items():
        d = d.where((F.col("var") != var) | ~F.col("code").isin(codes))
    return d
