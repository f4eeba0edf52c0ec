"""Small document tables with the awkward cases."""

import re

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, rows):
    """rows: (doc_id, text); other columns follow."""
    return spark.createDataFrame([(k, t, "en", "s", len(t or "")) for k, t in rows], SCHEMA)


AWKWARD = [
    (1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "a b c " * 4000), (6, "same text here"), (7, "same text here"),
    (7, "same text here"), (7, "another text of that id"), (None, "a second one without an id"), (None, None), (None, "no id, but a text é中\U0001f600 of some words"), (8, "x" * 20000),
]
