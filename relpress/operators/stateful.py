"""Filters that keep state between calls: what lives, as tables that a domain event changes by what it removes.

``remove(removed, depth)`` takes (var, code) gone at a search depth and returns the values (var, code) still supported;
``back(depth)`` goes to the state after the last call at that depth or above. Every state's tables are written once and never
changed, so going back forgets tables and moves no row. All agree with ``filters.scan`` on the same live values.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import CompressedRelation, Relation
from ..plans.staging import staged
from . import compression, filters

VALUE = ["var", "code"]


def _exploded(rows: DataFrame, key: str) -> DataFrame:
    return rows.select(key, F.explode("items").alias("x")).select(key, F.col("x.p").alias("var"), F.col("x.v").alias("code"))


class Kept:
    """The states of a search path: (depth, tables), the last of which is current."""

    def __init__(self, **tables: DataFrame):
        self.path = [(0, tables)]

    @property
    def now(self) -> dict[str, DataFrame]:
        return self.path[-1][1]

    def back(self, depth: int) -> None:
        while len(self.path) > 1 and self.path[-1][0] > depth:
            self.path.pop()

    def remove(self, removed: DataFrame, depth: int) -> DataFrame:
        live = staged(self.now["live"].join(removed.select(*VALUE), VALUE, "left_anti"), "live")
        self.path.append((depth, {"live": live, **self.changed(removed.select(*VALUE).distinct(), live)}))
        return self.supported()

    def changed(self, removed: DataFrame, live: DataFrame) -> dict[str, DataFrame]:
        raise NotImplementedError

    def supported(self) -> DataFrame:
        raise NotImplementedError


class Lists(Kept):
    """Value lists (var, code, tid), fixed, and the tuples that died."""

    def __init__(self, rel: Relation):
        self.lists = staged(_exploded(rel.numbered(), "tid"), "lists")
        super().__init__(live=rel.domains().select(*VALUE), dead=self.lists.select("tid").where("false"))

    def changed(self, removed, live):
        new = self.lists.join(removed, VALUE, "left_semi").select("tid").distinct().join(self.now["dead"], "tid", "left_anti")
        return {"dead": staged(self.now["dead"].unionByName(new), "dead")}

    def supported(self):
        return self.lists.join(self.now["live"], VALUE, "left_semi").join(self.now["dead"], "tid", "left_anti").select(*VALUE).distinct()


class Counters(Kept):
    """Lists and a count of live tuples for every value, lowered by those that die; with ``reset``, counted anew from the
    tuples left where these are fewer."""

    def __init__(self, rel: Relation, reset: bool = False):
        self.lists, self.reset = staged(_exploded(rel.numbered(), "tid"), "lists"), reset
        tuples = self.lists.select("tid").distinct()
        super().__init__(live=rel.domains().select(*VALUE), alive=staged(tuples, "alive"), counts=staged(self.lists.groupBy(*VALUE).agg(F.count("*").alias("n")), "counts"))

    def changed(self, removed, live):
        alive = self.now["alive"]
        new = staged(self.lists.join(removed, VALUE, "left_semi").select("tid").distinct().join(alive, "tid", "left_semi"), "dying")
        left = staged(alive.join(new, "tid", "left_anti"), "alive")
        if self.reset and left.count() < new.count():
            counts = self.lists.join(left, "tid", "left_semi").groupBy(*VALUE).agg(F.count("*").alias("n"))
        else:
            gone = self.lists.join(new, "tid", "left_semi").groupBy(*VALUE).agg(F.count("*").alias("g"))
            counts = self.now["counts"].join(gone, VALUE, "left").select(*VALUE, (F.col("n") - F.coalesce("g", F.lit(0))).alias("n")).where("n > 0")
        return {"alive": left, "counts": staged(counts, "counts")}

    def supported(self):
        return self.now["counts"].select(*VALUE).join(self.now["live"], VALUE, "left_semi")


class Bits(Kept):
    """Words of 64 tuples: those of each value, fixed, and those of the table, without the empty ones.

    For a changed column the table loses the removed values' words, or keeps the live ones', whichever values are fewer. A
    value whose last word still meets the table is done; the others are sought in all words.
    """

    def __init__(self, rel: Relation):
        x = _exploded(compression.dense(rel), "tid").select(*VALUE, F.shiftright("tid", 6).alias("word"), F.expr("shiftleft(1L, cast(tid & 63 AS INT))").alias("bit"))
        self.words = staged(x.groupBy(*VALUE, "word").agg(F.bit_or("bit").alias("bits")), "words")
        table = staged(self.words.groupBy("word").agg(F.bit_or("bits").alias("table")), "table")
        last = staged(self.words.groupBy(*VALUE).agg(F.min("word").alias("word")), "residues")
        super().__init__(live=rel.domains().select(*VALUE), table=table, last=last)

    def changed(self, removed, live):
        table = self.now["table"]
        before = self.now["live"]
        out = removed.join(before, VALUE, "left_semi").groupBy("var").agg(F.count("*").alias("out"))
        sizes = out.join(live.groupBy("var").agg(F.count("*").alias("stay")), "var", "left").orderBy("var").collect()  # a row a column
        for r in sizes:
            fewer = r["out"] < (r["stay"] or 0)
            side = (removed if fewer else live).where(F.col("var") == r["var"])
            met = self.words.join(side, VALUE, "left_semi").groupBy("word").agg(F.bit_or("bits").alias("met"))
            if fewer:
                table = table.join(met, "word", "left").select("word", F.col("table").bitwiseAND(F.bitwise_not(F.coalesce("met", F.lit(0).cast("bigint")))).alias("table"))
            else:
                table = table.join(met, "word").select("word", F.col("table").bitwiseAND(F.col("met")).alias("table"))
            table = table.where("table <> 0")
        table = staged(table, "table")
        alive = self.words.join(live, VALUE, "left_semi").join(table, "word").where(F.col("bits").bitwiseAND(F.col("table")) != 0)
        last = self.now["last"]
        held = alive.join(last, [*VALUE, "word"], "left_semi").select(*VALUE, "word")
        rest = alive.join(held, VALUE, "left_anti").groupBy(*VALUE).agg(F.min("word").alias("word"))
        return {"table": table, "last": staged(held.unionByName(rest), "residues")}

    def supported(self):
        return self.now["last"].select(*VALUE).join(self.now["live"], VALUE, "left_semi")


class Diagram(Kept):
    """Edges of a decision diagram that lie on a way from the root to the sink."""

    def __init__(self, rel: Relation):
        self.arity = rel.arity
        super().__init__(live=rel.domains().select(*VALUE), edges=staged(compression.diagram(rel), "edges"))

    def changed(self, removed, live):
        return {"edges": staged(filters.diagram_edges(self.now["edges"], self.arity, live), "edges")}

    def supported(self):
        return self.now["edges"].select(F.col("level").alias("var"), "code").distinct()


class Entries(Kept):
    """The compressed form: live heads, live rows of live heads, live default rows. A head dies with one of its items, without a
    look at its rows, or with its last row."""

    def __init__(self, rel: Relation, c: CompressedRelation):
        self.arity = c.arity
        super().__init__(live=rel.domains().select(*VALUE), heads=c.heads.select("entry", "items"), body=c.body, default=c.default)

    def _less(self, rows: DataFrame, removed: DataFrame, key: str) -> DataFrame:
        return rows.join(_exploded(rows, key).join(removed, VALUE, "left_semi").select(key).distinct(), key, "left_anti")

    def changed(self, removed, live):
        heads = self._less(self.now["heads"], removed, "entry")
        body = staged(self._less(self.now["body"].join(heads.select("entry"), "entry", "left_semi"), removed, "tid"), "body")
        heads = staged(heads.join(body.select("entry").distinct(), "entry", "left_semi"), "heads")
        return {"heads": heads, "body": body, "default": staged(self._less(self.now["default"], removed, "tid"), "default")}

    def supported(self):
        return filters.values_of(self.now["heads"]).unionByName(filters.values_of(self.now["body"])).unionByName(filters.values_of(self.now["default"])).distinct()

    def limits(self) -> DataFrame:
        """(entry, rows): live rows of each live entry, the default table as entry -1."""
        rest = self.now["default"].agg(F.count("*").alias("rows")).select(F.lit(-1).cast("bigint").alias("entry"), "rows")
        return self.now["body"].groupBy("entry").agg(F.count("*").alias("rows")).unionByName(rest)


def kept(rel: Relation, method: str, k: float = 0.4) -> Kept:
    """The state of a method over a relation."""
    if method in ("entries", "entries_slices"):
        return Entries(rel, compression.area_cover(rel, k, "min") if method == "entries" else compression.savings_slice(rel))
    makers = {"lists": Lists, "counters": Counters, "counters_reset": lambda r: Counters(r, True), "bits": Bits, "diagram": Diagram}
    if method not in makers:
        raise ValueError(f"no method {method!r}")
    return makers[method](rel)
