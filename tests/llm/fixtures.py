"""Small tables with what operators must stand: nulls, empty and long texts, repeated rows, columns with clashing names."""

import random

from pyspark.sql import types as T

WORDS = [f"w{i}" for i in range(400)]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def documents(spark, seed=1):
    rng = random.Random(seed)
    rows, k = [], 0

    def add(text, source="a", doc_id="next"):
        nonlocal k
        rows.append((k if doc_id == "next" else doc_id, text, "en", source, len(text or ""), "x", 7))
        k += 1

    for n in (1, 3, 4, 5, 6, 49, 50, 51, 120, 300):
        add(prose(rng, n), rng.choice(["a", "b", None]))
    base = prose(rng, 200).split()
    for change in (0, 0, 1, 3, 5, 20, 60):
        words = list(base)
        for _ in range(change):
            words[rng.randrange(len(words))] = rng.choice(WORDS)
        add(" ".join(words), "hot")
    for _ in range(12):
        add("Same Text\nsame text again " * 20, "hot")
    add("SAME TEXT\nSAME TEXT AGAIN " * 20, "b")
    add(None), add(""), add("   \t\n "), add("Été naïve 日本語 text wide <|endoftext|> it's", "é")
    add(prose(rng, 9000), "long")
    add("mail me.now%x@mail.example.com, a@b, x@y@z.org. 10.2.3.4 999.1.2.3.4 1.2.3.4.5 4111 1111 1111 1111 4111-1111-1111-1112 +1 (555) 010-9999 +49 30", "b")
    add('token = "0123456789abcdef0123456789abcdef01234567" and (415) 555-0199 or 5 -123', "b")
    add(prose(rng, 80), None), add(prose(rng, 80), "a", None), add(prose(rng, 60), None, None)
    rows.append(rows[3])
    rows.append(rows[12])
    schema = T.StructType([T.StructField("doc_id", T.LongType()), *[T.StructField(n, T.StringType()) for n in ("text", "lang", "source")], T.StructField("n_chars", T.LongType()), T.StructField("_text", T.StringType()), T.StructField("size", T.IntegerType())])
    return spark.createDataFrame(rows, schema), rows


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
