"""Odd documents and small tools for the operator tests."""

import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")
A = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty twenty-one twenty-two"
ODD = [
    (1, None, "en", None),
    (2, "", None, "s"),
    (3, "   \n\t ", "en", "s"),
    (4, "a", "en", "s"),
    (5, A, "en", "s"),
    (6, A, "en", "s"),
    (7, A.upper() + " and more", "en", "s"),
    (8, "x " * 400, "de", "s"),
    (9, ("A line of more than twenty characters\n" * 3 + "short\n" * 2), "fr", "s"),
    (10, "a line of more than twenty characters \n tail", "fr", "s"),
    (11, "\tA LINE of more than twenty characters", "fr", None),
    (12, "## ** $$ 1 2 3 <b> | & " + A, "en", "s"),
    (13, "mail me at jo.e@mail.example.com or +1 (212) 555-0100, ip 10.0.0.1, card 4111 1111 1111 1111", "en", "s"),
    (14, "日本語 ▁▁ é́ \x1c <|endoftext|> don't İ", "ja", "s"),
    (15, "word%d " * 3000 % tuple(range(3000)), "en", "s"),
    (15, "repeated id " + A, "en", "s"),
    (None, "no id here " + A, "en", "s"),
]
SCHEMA = "doc_id long, text string, lang string, source string"


def documents(spark, rows=ODD):
    """Rows with columns whose names clash with results of the operators."""
    return spark.createDataFrame(rows, SCHEMA).selectExpr("*", "1 as n_lines", "'x' as kept", "2 as n", "3 as component_id", "'y' as words", "0 as n_chars")


def empty(spark):
    return documents(spark).where("false")
