import pytest

from relpress.model import Constraint, Instance, Relation
from relpress.operators import mining

from .fixtures import EXAMPLE, example, sets_of

TOY = [(0, list("ABCDE")), (1, list("BCDE")), (2, list("CDE")), (3, list("ACDE")), (4, list("ABCE"))]


def test_toy_transactions(spark):
    t = spark.createDataFrame(TOY, "tid long, items array<string>")
    freq = {"".join(r["items"]): r["freq"] for r in mining.frequent_growth(t, 2).collect()}
    assert len(freq) == 27 and freq["CE"] == 5
    closed = {s: f for s, f in freq.items() if not any(set(s) < set(o) and f == g for o, g in freq.items())}
    assert closed == {"CE": 5, "CDE": 4, "ACE": 3, "BCE": 3, "BCDE": 2, "ABCE": 2, "ACDE": 2}
    assert {s for s in freq if not any(set(s) < set(o) for o in freq)} == {"BCDE", "ABCE", "ACDE"}
    assert {s for s, f in freq.items() if f >= 4} == {"E", "C", "D", "CE", "DE", "CD", "CDE"}


def test_mine_and_compress(spark):
    rel = example(spark)
    assert rel.mine("maximal", 2).count() == 11 and rel.mine("closed", 2).count() == 23 and rel.mine("frequent", 2).count() == 65
    assert [r["freq"] for r in rel.mine("topk", k=2).collect()] == [7, 6]
    assert sets_of(rel.compress(s_min=2).heads) and rel.compress("cartesian").count() <= 11 and rel.compress("bitset").count() == 15
    with pytest.raises(ValueError):
        rel.compress("nothing")


def test_instance(spark):
    rel = example(spark)
    inst = Instance({0: [0, 1], 1: [0, 1, 2], 2: [0, 1, 2], 3: [0, 1, 2, 3], 4: [0, 1, 2]}, [Constraint(rel, [0, 1, 2, 3, 4])])
    assert {tuple(r) for r in inst.solve_by_join(spark).collect()} == set(EXAMPLE)
    assert inst.propagate(spark).count() == 15
    assert inst.solve(spark).first()["status"] == "sat"


def test_forbidden_tuples(spark):
    rel = Relation(spark.createDataFrame([(0, 0)], "a int, b int"), ["a", "b"], sign=False)
    assert {tuple(r) for r in rel.allowed([[0, 1], [0, 1]]).df.collect()} == {(0, 1), (1, 0), (1, 1)}
