import corpus_pipeline as P
import pytest

from relpress.llm.common import written

from .helpers import WORD, numbered, table
from .test_operators import brute_lines, brute_near


@pytest.fixture(scope="module")
def stages(spark):
    docs = table(spark, numbered(6))
    out = [docs]
    for i, (_, f) in enumerate(P.STAGES):
        out.append(written(spark, f(spark, out[-1], ""), f"test{i}"))
    return out


def rows(df):
    return [(r["doc_id"], r["text"]) for r in df.collect()]


def test_each_stage_against_brute_force(stages):
    docs, known, lines, near, mixed, coded = stages
    assert all(s.columns == docs.columns for s in (known, lines, near, mixed))
    # Texts without a letter are rejected; clean ones stay.
    assert {i for i, _ in rows(known)} == {i for i, t in rows(docs) if t and any(c.isalpha() for c in t)}
    want = {i: t for i, t in brute_lines(rows(known), 5).items() if WORD.search(t)}
    assert dict(rows(lines)) == want
    assert {i for i, _ in rows(near)} == {i for i, (_, c) in brute_near(rows(lines), 80).items() if i == c}
    kept = dict(rows(near))
    assert all(kept[i] == t for i, t in rows(mixed)) and len(rows(mixed)) == coded.count()


def test_stages_take_an_empty_table(spark, stages):
    nothing = stages[0].limit(0)
    for _, f in P.STAGES:
        assert f(spark, nothing, "").count() == 0
