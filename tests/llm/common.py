"""Rows that every operator must take: nulls, empty and very long texts, ties, repeated rows, clashing columns."""

from __future__ import annotations

import random

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, _size long, fp string, key string, _block string, score double, p_toxic double, _row string, word string, did long, `odd name` string"


def rows(texts, source=lambda k: f"s{k % 3}"):
    return [(k, t, "en", source(k), None, 1, 2, "f", "k", "b", 0.5, 0.1, "r", "w", 7, "o") for k, t in texts]


def edge_texts():
    rng = random.Random(9)
    words = [f"word{k}" for k in range(400)]
    long = " ".join(rng.choice(words) for _ in range(30_000))
    some = " ".join(rng.choice(words) for _ in range(120))
    return [
        (1, None), (2, ""), (3, " \t\n"), (4, "one"), (5, some), (6, some), (6, some), (None, "no id at all here"), (7, some.replace(" ", "  ")), (8, long), (9, "x" * 50_000),
        (10, "same same same same same same same same"), (11, "Café \U0001f600 naïve ß"), (12, some + " tail"), (-5, "negative id " + some[:200]), (13, "\n\n\r\n"),
    ]


def edge(spark):
    return spark.createDataFrame(rows(edge_texts(), lambda k: None if k is None or k % 4 == 0 else f"s{k % 3}"), SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)
