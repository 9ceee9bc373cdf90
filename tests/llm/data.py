"""A small table with the awkward cases: nulls, empty and long texts, ties, repeated rows and clashing column names."""

import random

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, fp string, k0 int, id int, t string, label string, word string"


def docs(spark, rows=None):
    rng = random.Random(3)
    words = {
        "en": "the and of thing with there water stone every under light often house again field".split(),
        "de": "der und die straße über nicht zwischen wächst größer wald immer wieder schön ganz".split(),
    }

    def prose(lang, n):
        return " ".join(rng.choice(words[lang]) for _ in range(n)).capitalize() + "."

    if rows is None:
        long = "\n".join(prose("en", 40) for _ in range(60))
        base = prose("en", 150)
        rows = [
            (0, prose("en", 60), "en"), (1, prose("de", 60), "de"), (2, None, "en"), (3, "", "de"), (4, "12 34 !!", None), (5, "\n \t\n", None),
            (6, base, "en"), (7, base, "en"), (8, base + " extra words", None), (9, long, "en"), (10, "Lead " + base, "en"),
            (11, "one", None), (12, "one two", None), (13, long + "\n" + prose("de", 30), "de"), (14, prose("de", 80), "de"), (14, prose("de", 80), "de"),
            (15, "same row", "en"), (15, "same row", "en"), (None, prose("en", 30), "en"), (16, "naïve café \U0001f600 \x1c x\x1dy <|endoftext|> z", "en"),
        ]
    return spark.createDataFrame([(i, t, g, f"s{(i or 0) % 3}" if i != 5 else None, len(t or ""), "x", 1, 2, "t", "l", "w") for i, t, g in rows], SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)
