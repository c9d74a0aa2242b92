"""Constraint problems: propagation to the fixpoint, search with consistency kept, breadth search and solving by joins.

The cluster forms (``propagate``, ``by_join``, ``frontier``, ``check``) are DataFrame plans over all constraints at once.
Depth-first search is sequential by nature and runs one instance a task; its relations go with the task, so they are
checked against ``KERNEL_TUPLES`` first.
"""

from __future__ import annotations

import io
import json
import pickle
import time
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Relation
from ..operators import local
from ..sources import workloads as W
from . import kernels, metrics
from .staging import ship, staged

#: Tuples of a relation that a search task takes.
KERNEL_TUPLES = 1_000_000


# Cluster forms --------------------------------------------------------------------------------------------------------


def propagate(constraints: list[tuple[Relation, list[int]]], domains: DataFrame) -> tuple[DataFrame, int]:
    """Arc-consistent domains (var, code) and the rounds taken; an empty domain empties all.

    Tuples are kept as rows of their items. A round drops the tuples that hold a value removed in the round before, all
    constraints in one plan, and keeps the values that each constraint on their variable supports: a value with a live
    tuple, or, in a table of forbidden tuples, one with fewer live tuples than the others' domains have combinations.
    """
    spark = domains.sparkSession
    parts = []
    for cid, (rel, scope) in enumerate(constraints):
        first = {v: c for c, v in reversed(list(zip(rel.scope, scope)))}
        d = rel.df
        for c, v in zip(rel.scope, scope):  # a variable that stands twice has one value
            d = d if first[v] == c else d.where(F.col(c) == F.col(first[v]))
        items = F.array(*[F.struct(F.lit(v).alias("var"), F.col(c).cast("int").alias("code")) for v, c in first.items()])
        parts.append(d.select(F.lit(cid).alias("cid"), items.alias("x")).distinct())
    rows = reduce(DataFrame.unionByName, parts).withColumn("tid", F.monotonically_increasing_id())
    rows = staged(rows.select("cid", "tid", F.explode("x").alias("x")).select("cid", "tid", "x.var", "x.code"), "tuples")
    asked = spark.createDataFrame([(cid, v, bool(rel.sign)) for cid, (rel, scope) in enumerate(constraints) for v in dict.fromkeys(scope)], "cid int, var int, sign boolean")
    live = staged(domains.select("var", "code").distinct(), "domains")
    gone = rows.select("var", "code").distinct().join(live, ["var", "code"], "left_anti")
    n, rounds = live.count(), 0
    while True:
        rounds += 1
        dead = rows.join(gone, ["var", "code"], "left_semi").select("cid", "tid").distinct()
        rows = staged(rows.join(dead, ["cid", "tid"], "left_anti"), f"tuples{rounds}")
        held = rows.groupBy("cid", "var", "code").agg(F.count("*").alias("n"))
        size = live.groupBy("var").agg(F.count("*").alias("size"))
        every = asked.join(size, "var").groupBy("cid").agg(F.product("size").alias("every"))
        value = live.join(asked, "var").join(held, ["cid", "var", "code"], "left").join(every, "cid").join(size, "var")
        lost = value.where(F.when(F.col("sign"), F.col("n").isNull()).otherwise(F.coalesce("n", F.lit(0)) >= F.col("every") / F.col("size"))).select("var", "code").distinct()
        gone = staged(lost, f"lost{rounds}")
        live = staged(live.join(gone, ["var", "code"], "left_anti"), f"domains{rounds}")
        now = live.count()
        if now == n:
            break
        n = now
    wiped = domains.select("var").distinct().join(live.select("var").distinct(), "var", "left_anti")
    return live.join(wiped.select(F.lit(1).alias("_w")).limit(1), F.lit(True), "left_anti"), rounds


def _table(rel: Relation, scope: list[int]) -> DataFrame:
    """A relation's tuples in columns of its variables; a variable that stands twice must agree."""
    d = rel.df.select(*[F.col(c).cast("int").alias(f"_{p}") for p, c in enumerate(rel.scope)])
    first: dict[int, int] = {}
    for p, v in enumerate(scope):
        if v in first:
            d = d.where(F.col(f"_{p}") == F.col(f"_{first[v]}"))
        first.setdefault(v, p)
    return d.select(*[F.col(f"_{p}").alias(f"v{v}") for v, p in first.items()]).distinct()


def by_join(constraints: list[tuple[Relation, list[int]]], domains: dict[int, list[int]] | None = None) -> DataFrame:
    """All solutions, one column a variable (v0, v1, ...): constraints joined on shared variables, most shared first.

    ``domains`` bounds the variables; those that no table of allowed tuples holds take all their values. A table of
    forbidden tuples is an anti-join once its variables are bound. Problems that fall apart give the product of their
    parts, as their solutions do.
    """
    left = [i for i, (rel, _) in enumerate(constraints) if rel.sign]
    forbidden = [i for i, (rel, _) in enumerate(constraints) if not rel.sign]
    if forbidden and domains is None:
        raise ValueError("a table of forbidden tuples needs the domains of its variables")

    def table(i: int) -> DataFrame:
        d = _table(*constraints[i])
        for v, codes in (domains or {}).items():
            d = d.where(F.col(f"v{v}").isin(codes)) if f"v{v}" in d.columns else d
        return d

    out = table(left.pop(0)) if left else constraints[0][0].df.sparkSession.range(1).select(F.lit(0).alias("_root"))
    while left:
        i = max(left, key=lambda j: (len({f"v{v}" for v in constraints[j][1]} & set(out.columns)), -j))
        left.remove(i)
        d = table(i)
        shared = [c for c in d.columns if c in out.columns]
        out = out.join(d, shared) if shared else out.crossJoin(d)
    for v, codes in (domains or {}).items():
        if f"v{v}" not in out.columns:
            out = out.withColumn(f"v{v}", F.explode(F.array(*[F.lit(x) for x in codes]).cast("array<int>")))
    for i in forbidden:
        d = _table(*constraints[i])
        out = out.join(d, d.columns, "left_anti")
    return out.select(*sorted((c for c in out.columns if c != "_root"), key=lambda c: int(c[1:])))


def check(constraints: list[tuple[Relation, list[int]]], solutions: DataFrame) -> DataFrame:
    """The rows of ``solutions`` (columns v0, v1, ...) that satisfy every constraint."""
    for rel, scope in constraints:
        d = rel.df.select(*[F.col(c).cast("int").alias(f"_{p}") for p, c in enumerate(rel.scope)])
        solutions = solutions.join(d, reduce(lambda a, b: a & b, [F.col(f"v{v}") == F.col(f"_{p}") for p, v in enumerate(scope)]), "left_semi" if rel.sign else "left_anti")
    return solutions


def frontier(constraints: list[tuple[Relation, list[int]]], domains: DataFrame, width: int | None = None) -> DataFrame:
    """Breadth search: open nodes are rows; each round assigns one variable to all and keeps nodes every constraint can extend.

    ``width`` bounds the open nodes after a round (an incomplete search); None keeps all.
    """
    spark = domains.sparkSession
    order = [r["var"] for r in domains.groupBy("var").count().orderBy("count", "var").collect()]
    nodes = spark.createDataFrame([(0,)], "_root int")
    done: list[int] = []
    for var in order:
        nodes = nodes.crossJoin(domains.where(F.col("var") == var).select(F.col("code").cast("int").alias(f"v{var}")))  # a finite domain
        done.append(var)
        for rel, scope in constraints:
            if var in scope:
                at = [(p, v) for p, v in enumerate(scope) if v in done]
                if not rel.sign and len(at) < len(scope):
                    continue  # forbidden tuples tell nothing before all their variables have values
                d = rel.df.select(*[F.col(rel.scope[p]).cast("int").alias(f"_{p}") for p, _ in at]).distinct()
                nodes = nodes.join(d, reduce(lambda a, b: a & b, [F.col(f"v{v}") == F.col(f"_{p}") for p, v in at]), "left_semi" if rel.sign else "left_anti")
        if width is not None:
            nodes = nodes.orderBy(*[f"v{v}" for v in done]).limit(width)
        nodes = staged(nodes, f"open{var}")
    return nodes.select(*[f"v{v}" for v in sorted(done)])


# Search kernel --------------------------------------------------------------------------------------------------------


def depth_first(sizes: list[int], scopes: list[list[int]], tables: list, time_limit_s: float = 1800.0, var_order: str = "smallest", clock=time.process_time) -> dict:
    """Search for one solution: status, solution, nodes (values tried) and cells looked at.

    Next variable: the smallest live domain, or 'ratio' (domain over constraints on it), or 'first'; values ascending.
    """
    on: list[list[int]] = [[i for i, s in enumerate(scopes) if v in s] for v in range(len(sizes))]
    began, nodes = clock(), 0

    def consistent(live, state, queue):
        """Filters constraints until none changes a domain; False on a wipe-out, None when time is up."""
        while queue:
            if clock() - began > time_limit_s:
                return None
            i, changed = queue.popitem()
            scope = scopes[i]
            here = {p: live[v] for p, v in enumerate(scope)}
            seek = [p for p, v in enumerate(scope) if live[v].sum() > 1 or p in changed]
            state[i], found = tables[i].filter(state[i], here, sorted(changed), seek)
            for p in seek:
                v = scope[p]
                left = live[v] & found[p]
                if not left.any():
                    return False
                if left.sum() < live[v].sum():
                    live[v] = left
                    for j in on[v]:
                        if j != i:
                            queue.setdefault(j, set()).update(q for q, w in enumerate(scopes[j]) if w == v)
        return True

    def cells() -> int:  # constraints may share a filter
        return sum(t.cells for t in {id(t): t for t in tables}.values())

    live = [np.ones(s, bool) for s in sizes]
    state = [t.start() for t in tables]
    first = consistent(live, state, {i: set(range(len(s))) for i, s in enumerate(scopes)})
    if not first:
        return {"status": "unsat" if first is False else "timeout", "solution": None, "nodes": 0, "cells": cells(), "cpu_s": clock() - began}
    stack = [(live, state, None)]
    status, solution = "unsat", None
    while stack:
        if clock() - began > time_limit_s:
            status = "timeout"
            break
        live, state, choice = stack.pop()
        if choice is not None:
            v, code = choice
            nodes += 1
            live, state = list(live), list(state)
            live[v] = np.arange(sizes[v]) == code
            went = consistent(live, state, {i: {p for p, w in enumerate(scopes[i]) if w == v} for i in on[v]})
            if went is None:
                status = "timeout"
                break
            if not went:
                continue
        free = [v for v in range(len(sizes)) if live[v].sum() > 1]
        if not free:
            status, solution = "sat", [int(np.argmax(d)) for d in live]
            break
        v = min(free, key={"smallest": lambda x: (live[x].sum(), x), "ratio": lambda x: (live[x].sum() / max(1, len(on[x])), x), "first": lambda x: x}[var_order])
        stack += [(live, state, (v, int(code))) for code in np.flatnonzero(live[v])[::-1]]
    return {"status": status, "solution": solution, "nodes": nodes, "cells": cells(), "cpu_s": clock() - began}


def packed(relations: DataFrame) -> DataFrame:
    """(rel_id, tuples, blob): each relation of (rel_id, vals) as one array, made in the task that gathers it.

    A search works on whole relations, so they are bounded first: more than ``KERNEL_TUPLES`` tuples are an error.
    """
    spark = relations.sparkSession
    ship(spark)
    most = relations.groupBy("rel_id").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
    if most > KERNEL_TUPLES:
        raise ValueError(f"{most} tuples in a relation: more than a search task takes; use propagate and by_join")

    def pack(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        rows = local.ordered(np.array(group["vals"].tolist(), np.int32))
        out = io.BytesIO()
        np.save(out, rows)
        return pd.DataFrame({"rel_id": [key[0]], "tuples": [len(rows)], "blob": [out.getvalue()]})

    return staged(relations.groupBy("rel_id").applyInPandas(pack, "rel_id string, tuples bigint, blob binary"), "packed")


def formed(blobs: DataFrame, forms: list[str], k: float) -> DataFrame:
    """(rel_id, form, body): each relation in each form, a task each."""
    wanted = blobs.sparkSession.createDataFrame([(f,) for f in forms], "form string")

    def make(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        rows = np.load(io.BytesIO(group["blob"].iloc[0])).astype(np.int64)
        return pd.DataFrame({"rel_id": [key[0]], "form": [key[1]], "body": [pickle.dumps(kernels.FORMS[key[1]](rows, k))]})

    each = blobs.crossJoin(F.broadcast(wanted))  # a few names
    return staged(each.repartition(max(1, blobs.count() * len(forms)), "rel_id", "form").groupBy("rel_id", "form").applyInPandas(make, "rel_id string, form string, body binary"), "forms")


RUNS = "method string, workload string, instance_id string, status string, nodes bigint, cells bigint, cpu_s double, solution array<int>"


def search_all(relations: DataFrame, instances: list[dict], methods: tuple[str, ...], time_limit_s: float = 1800.0, k: float = 0.4, var_order: str = "smallest") -> DataFrame:
    """(method, workload, instance_id, status, nodes, cells, cpu_s, solution): every method on every instance, one task each.

    ``relations`` is (rel_id, vals); an instance has workload, id, sizes (of the domains) and constraints (rel_id, scope).
    Relations are compressed once, a task each; the task of an instance gets them by a join. Only instances pass the driver.
    """
    spark = relations.sparkSession
    blobs = packed(relations)
    forms = sorted({f for _, f in (kernels.METHODS[m] for m in methods) if f})
    rows = [(m, kernels.METHODS[m][1], x["workload"], x["id"], json.dumps([x["sizes"], x["constraints"]]) if not n else None, r) for m in methods for x in instances for n, r in enumerate(sorted({r for r, _ in x["constraints"]}))]
    todo = spark.createDataFrame(rows, "method string, form string, workload string, instance_id string, spec string, rel_id string").join(blobs, "rel_id")
    todo = todo.join(formed(blobs, forms, k), ["rel_id", "form"], "left") if forms else todo.withColumn("body", F.lit(None).cast("binary"))

    def solve(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        sizes, constraints = json.loads(next(s for s in group["spec"] if s))
        rows = {r: np.load(io.BytesIO(b)).astype(np.int64) for r, b in zip(group["rel_id"], group["blob"])}
        bodies = {r: pickle.loads(b) for r, b in zip(group["rel_id"], group["body"]) if b is not None}
        made: dict = {}
        for r, scope in constraints:
            at = (r, *[sizes[v] for v in scope])
            if at not in made:
                made[at] = kernels.build(key[0], rows[r], list(at[1:]), k, bodies.get(r))
        tables = [made[(r, *[sizes[v] for v in scope])] for r, scope in constraints]
        out = depth_first(sizes, [s for _, s in constraints], tables, time_limit_s, var_order)
        return pd.DataFrame([{"method": key[0], "workload": key[1], "instance_id": key[2], **{x: out[x] for x in ("status", "nodes", "cells", "cpu_s")}, "solution": out["solution"]}])

    todo = todo.repartition(len(methods) * len(instances), "method", "workload", "instance_id")  # a search is a task's worth
    return todo.groupBy("method", "workload", "instance_id").applyInPandas(solve, RUNS)


def search(spark: SparkSession, instances: list[tuple[str, list[int], list[tuple[int, list[int]]]]], relations: list[Relation], methods: tuple[str, ...] = ("tabular", "entries", "bits"), time_limit_s: float = 1800.0, k: float = 0.4, var_order: str = "smallest") -> DataFrame:
    """``search_all`` for a few relations given as such: an instance is (id, domain sizes, constraints), a constraint
    (number of its relation, scope)."""
    every = reduce(DataFrame.unionByName, [r.df.select(F.lit(str(i)).alias("rel_id"), F.array(*[F.col(c).cast("int") for c in r.scope]).alias("vals")) for i, r in enumerate(relations)])
    listed = [{"workload": "", "id": name, "sizes": list(sizes), "constraints": [(str(r), list(scope)) for r, scope in constraints]} for name, sizes, constraints in instances]
    return search_all(every, listed, tuple(methods), time_limit_s, k, var_order).drop("workload")


def word_grid(n: int) -> list[list[int]]:
    """Scopes of an open n by n grid: a row or a column is one word, cells are variables 0 to n*n - 1."""
    return [[r * n + c for c in range(n)] for r in range(n)] + [[r * n + c for r in range(n)] for c in range(n)]


def scattered(seed: int, variables: int, constraints: int, arity: int, relations: int) -> list[tuple[int, list[int]]]:
    """Scopes by arithmetic on the seed: distinct variables each, relations in turn."""
    out, x = [], seed * 7919 + 12345
    for i in range(constraints):
        scope: list[int] = []
        while len(scope) < arity:
            x = (x * 1103515245 + 12345) % 2147483648
            v = x // 65536 % variables
            if v not in scope:
                scope.append(v)
        out.append((i % relations, scope))
    return out


# Queries --------------------------------------------------------------------------------------------------------------

QUERIES = {}
ORACLE_SQL = {}

#: Variables: 0 nation, 1 region, 2 segment, 3 a second nation of the region, 4 status, 5 priority. Values removed at the start.
_SHOP = [("nation_region", [0, 1]), ("nation_segment", [0, 2]), ("nation_region", [3, 1]), ("status_priority", [4, 5])]
_SHOP_OUT = {1: [0, 4], 2: [65], 0: [3, 8, 13], 5: [1, 2]}


def _shop(spark, sf):
    pairs = {n: W.relation(spark, sf, q, n) for n, q in W.pairs().items()}
    constraints = [(pairs[n], scope) for n, scope in _SHOP]
    values = [rel.df.select(F.lit(v).alias("var"), F.col(c).alias("code")) for rel, scope in constraints for v, c in zip(scope, rel.scope)]
    domains = reduce(DataFrame.unionByName, values).distinct()
    for var, codes in _SHOP_OUT.items():
        domains = domains.where((F.col("var") != var) | ~F.col("code").isin(codes))
    return constraints, domains


def _shop_sql() -> str:
    sources = {n: f"({W.plain(q)})" for n, q in W.pairs().items()}
    seen: dict[int, str] = {}
    tables, where = [], []
    for i, (n, scope) in enumerate(_SHOP):
        tables.append(f"{sources[n]} AS t{i}")
        for p, v in enumerate(scope):
            here = f"t{i}.c{p}"
            where += [f"{seen[v]} = {here}"] if v in seen else []
            seen.setdefault(v, here)
    where += [f"{seen[v]} NOT IN ({', '.join(map(str, c))})" for v, c in _SHOP_OUT.items()]
    return f"SELECT {', '.join(f'{seen[v]} AS v{v}' for v in sorted(seen))} FROM {', '.join(tables)} WHERE {' AND '.join(where)}"


def _query(oracle=None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLE_SQL[f.__name__] = oracle
        return f

    return add


# The constraints form a tree, on which arc-consistent values are exactly those of solutions.
@_query(f"WITH sol AS ({_shop_sql()}) " + " UNION ".join(f"SELECT {v} AS var, v{v} AS code FROM sol" for v in range(6)))
def propagate_fixpoint(spark, sf):
    return propagate(*_shop(spark, sf))[0]


@_query(_shop_sql())
def solve_by_join(spark, sf):
    constraints, domains = _shop(spark, sf)
    found = by_join(constraints)
    for var, codes in _SHOP_OUT.items():
        found = found.where(~F.col(f"v{var}").isin(codes))
    return found


@_query(f"SELECT count(*) AS n FROM ({_shop_sql()})")
def count_solutions(spark, sf):
    return frontier(*_shop(spark, sf)).agg(F.count("*").alias("n"))


def _grid_sql(n: int, length_sql: str) -> str:
    rows = [f"w r{i}" for i in range(n)] + [f"w k{i}" for i in range(n)]
    meets = " AND ".join(f"r{r}.c{c} = k{c}.c{r}" for r in range(n) for c in range(n))
    cells = ", ".join(f"r{r}.c{c} AS v{r * n + c}" for r in range(n) for c in range(n))
    return f"WITH w AS ({length_sql}) SELECT {cells} FROM {', '.join(rows)} WHERE {meets}"


@_query(f"SELECT count(*) AS n, CAST(sum(v0) AS BIGINT) AS s FROM ({_grid_sql(2, W.plain(W.words(2, 'es', True)))})")
def wordgrid_solutions(spark, sf):
    words = W.relation(spark, sf, W.words(2, "es"))
    found = by_join([(words, scope) for scope in word_grid(2)])
    return check([(words, scope) for scope in word_grid(2)], found).agg(F.count("*").alias("n"), F.sum("v0").alias("s"))


@_query(
    "SELECT 'grid' AS workload, 1 AS instances, 4 AS max_vars, (SELECT count(DISTINCT c) FROM (SELECT c0 AS c FROM w UNION ALL SELECT c1 FROM w)) AS max_values, 1 AS max_relations, (SELECT count(*) FROM w) AS max_tuples, 2 AS max_columns, 4 AS max_constraints".join((f"WITH w AS ({W.plain(W.words(2, 'es', True))}) ", ""))
)
def workload_characteristics(spark, sf):
    """Sizes of the instances of a workload, here a word grid of two by two."""
    words = W.relation(spark, sf, W.words(2, "es"))
    scopes = word_grid(2)
    variables = spark.createDataFrame([("grid", "g", v) for v in range(4)], "workload string, instance_id string, var int")
    codes = words.df.select(F.explode(F.array("c0", "c1")).alias("code")).distinct()
    domains = variables.select("instance_id", "var").crossJoin(codes)
    constraints = spark.createDataFrame([("g", i, "w", 2) for i in range(len(scopes))], "instance_id string, cid int, rel_id string, arity int")
    return metrics.characteristics(variables, domains, constraints, words.df.agg(F.count("*").alias("tuples")).select(F.lit("w").alias("rel_id"), "tuples"))


@_query(
    " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS tuples, {a} AS arity, count(*) * {a} AS cells FROM ({W.plain(q)})" for n, q, a in (("booleans_large", W.booleans_large(), 18), ("booleans_small", W.booleans_small(), 15), ("modular", W.modular(2500, 20), 7), ("words4", W.words(4, "en", True), 4), ("words8", W.words(8, None, True), 8), ("products", W.products(), 3), ("configurator", W.configurator(), 10), ("labelled", W.labelled(), 4), ("dense", W.dense(), 4), ("dense_quantity", W.dense_quantity(), 5)))
)
def workload_sizes(spark, sf):
    queries = {"booleans_large": W.booleans_large(), "booleans_small": W.booleans_small(), "modular": W.modular(2500, 20), "words4": W.words(4), "words8": W.words(8, None), "products": W.products(), "configurator": W.configurator(), "labelled": W.labelled(), "dense": W.dense(), "dense_quantity": W.dense_quantity()}
    parts = []
    for n, q in queries.items():
        rel = W.relation(spark, sf, q)
        parts.append(metrics.cells(rel).select(F.lit(n).alias("name"), "tuples", "arity", "cells"))
    return reduce(DataFrame.unionByName, parts)
