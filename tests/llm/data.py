"""Small inputs with the cases every operator has to stand: nulls, empty and long texts, ties, repeated rows, clashing columns."""

import random

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _text string, fp long, tk long, digest string, gram long"
TAIL = ("x", 1, 2, "y", 3)
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon été über niño".split()


def prose(n, seed):
    r = random.Random(seed)
    out = []
    for i in range(n):
        w = r.choice(WORDS) + str(r.randrange(400))
        out.append(w.capitalize() + "," if r.random() < 0.1 else w)
        if i % 13 == 12:
            out.append("\n")
    return " ".join(out)


def rows():
    texts = [
        None, "", "   \n\t ", "one", "One two THREE", prose(60, 1), prose(60, 1), prose(61, 1), prose(300, 2), prose(300, 2) + " tail", "head " + prose(300, 2),
        "spam spam spam spam " * 40, "a*b #c $d | <e> & % " * 30, "Line one is here\nLine one is here\nLine two\n\nLine one is here", prose(3000, 3), "aaaa" * 200,
        "nbsp inside  em \x1f unit", "ends with é, and Ünï. done",
    ]
    out = [(i, t, "en" if i % 3 else None, f"s{i % 4}" if i % 5 else None, len(t or "")) for i, t in enumerate(texts)]
    out.append(out[8])  # a repeated row
    out.append((None, prose(80, 9), "en", "s0", 1))  # no id
    return [(*r, *TAIL) for r in out]


def frame(spark, data=None):
    return spark.createDataFrame(rows() if data is None else data, SCHEMA)
