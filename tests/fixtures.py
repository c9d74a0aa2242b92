"""The worked examples as literal rows."""

EXAMPLE = [
    (0, 0, 0, 0, 2), (0, 0, 0, 1, 2), (0, 2, 0, 2, 0), (0, 0, 1, 1, 2), (0, 0, 1, 2, 0), (0, 0, 1, 3, 2),
    (1, 0, 2, 1, 1), (1, 0, 2, 3, 0), (1, 1, 2, 0, 1), (1, 1, 2, 2, 2), (1, 1, 2, 3, 0),
]
X = ["x0", "x1", "x2", "x3", "x4"]


def example(spark):
    from relpress.model import Relation

    return Relation(spark.createDataFrame(EXAMPLE, ", ".join(f"{c} int" for c in X)), X)


def sets_of(df):
    return {(tuple((x["p"], x["v"]) for x in r["items"]), r["freq"]) for r in df.collect()}


def brute_frequent(rows, s_min):
    """All frequent itemsets of tuples, by enumeration."""
    from itertools import combinations

    found = {}
    for row in set(rows):
        items = list(enumerate(row))
        for n in range(1, len(items) + 1):
            for c in combinations(items, n):
                found[c] = found.get(c, 0) + 1
    return {k: f for k, f in found.items() if f >= s_min}


def brute_closed(freq):
    return {(k, f) for k, f in freq.items() if not any(set(k) < set(o) and f == g for o, g in freq.items())}


def brute_maximal(freq):
    return {(k, f) for k, f in freq.items() if not any(set(k) < set(o) for o in freq)}
