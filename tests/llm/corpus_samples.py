"""Small tables with the odd cases."""

from pyspark.sql import types as T

DOCS = T.StructType([T.StructField(n, t) for n, t in (("doc_id", T.LongType()), ("text", T.StringType()), ("lang", T.StringType()), ("source", T.StringType()), ("n_chars", T.LongType()))])

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def prose(seed: int, n: int) -> str:
    import random

    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + r.choice(["", "", ".", ","]) for _ in range(n))


ODD = [
    (1, None, None, None, None),
    (2, "", "en", "a", 0),
    (3, "   \n\t ", "en", "a", 6),
    (4, "one", "de", "a", 3),
    (5, prose(5, 200), "en", "a", 0),
    (6, prose(5, 200), "en", "b", 0),
    (7, prose(5, 200) + " and a tail", "en", "b", 0),
    (8, prose(8, 20_000), "en", "a", 0),
    (9, "Ünïcode ŝtring 東京 🙂 " * 30, "fr", "c", 0),
    (9, "Ünïcode ŝtring 東京 🙂 " * 30, "fr", "c", 0),
    (10, "aaaa " * 400, "en", "c", 0),
    (None, prose(11, 60), "en", "a", 0),
]
