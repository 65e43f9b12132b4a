"""Rows that every operator has to bear: nulls, empty and long texts, ties, repeats, clashing extra columns."""

PROSE = " ".join(f"word{i % 97} and{i % 31}" for i in range(120))
EDGES = [
    (None, PROSE, "en", "s", 1),
    (1, None, "en", "s", None),
    (2, "", None, None, 0),
    (3, " \t\n\x0b\x0c\r ", "en", "s", 3),
    (4, PROSE, "en", "s", 4),
    (4, PROSE, "en", "s", 4),
    (5, PROSE, "fr", None, 5),
    (6, PROSE + " tail", "en", "s", 6),
    (7, "longword" * 5000, "de", "s", 7),
    (8, " lead  two   spaces nbsp ▁mark trailing ", "en", "s", 8),
    (9, "line one\nline one\n\nline one\nother\n", "en", "s", 9),
    (10, "a a a a a a b c d a b c", "en", "s", 10),
    (11, "é̃\U0001f600 \x00 ﻿ <s> <unk> |||", "es", "s", 11),
    (12, "\n".join(PROSE for _ in range(120)), "en", "s", 12),
    (13, "12345 !!! 999", "en", "s", 13),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def edges(spark, clash: str = ""):
    df = spark.createDataFrame(EDGES, SCHEMA)
    for c in clash.split():
        df = df.selectExpr("*", f"cast(doc_id as string) as {c}")
    return df
