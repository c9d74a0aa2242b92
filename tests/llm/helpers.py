"""Small document tables with every awkward case, and brute-force versions of what operators find."""

import random
import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, i long, h long, score double, rank int"
SYLLABLES = ["an", "ber", "co", "dou", "el", "fri", "gan", "ho", "il", "ju", "ka", "lo", "mi", "nor", "ot", "pre"]


def word(rng):
    return "".join(rng.choice(SYLLABLES) for _ in range(rng.randint(1, 3)))


def line(rng, n=8):
    return " ".join(word(rng) for _ in range(n)).capitalize() + "."


def texts(seed=1, n=24):
    """Random texts, exact and near copies, shared passages, and odd ones."""
    rng = random.Random(seed)
    passage = "\n".join(line(rng, 14) for _ in range(5))
    base = ["\n".join(line(rng) for _ in range(rng.randint(1, 12))) for _ in range(n)]
    out = list(base)
    out += [base[0], base[0], base[3]]
    words = base[5].split(" ")
    out += [" ".join([*words[:7], "changed", *words[8:]]), base[7] + "\n" + passage, passage + "\n" + base[8], base[9] + "\n" + passage]
    out += ["", None, " \t\n ", "the", "a" * 700, "ab" * 400, "é漢字🙂 naïve 'll don't <|endoftext|> x y", "\n\n\n", "one two three four five", "12345 !!!"]
    return out


def table(spark, rows):
    """A table of (doc_id, text) rows with columns whose names clash with those inside the operators."""
    return spark.createDataFrame([(i, t, ("en", "de", None)[(i or 0) % 3], ("s1", "s2", "s2", None)[(i or 0) % 4], len(t or ""), 7, 7, 0.5, 1) for i, t in rows], SCHEMA)


def numbered(seed=1, n=24):
    return [(k * 3 + 1, t) for k, t in enumerate(texts(seed, n))]
