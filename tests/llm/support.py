"""Small corpora with every odd case, and plain versions of what the operators say."""

from __future__ import annotations

import random
import re
import string

LOWER = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
#: Columns whose names clash with those the operators use inside.
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, chunk int, kd string, r_words string, fp double, w array<string>, word string, score string"


def space_words(text: str | None) -> list[str]:
    return [w for w in re.split("[ \x09-\x0d]+", text or "") if w]


def corpus(seed: int = 1, n: int = 60) -> list[tuple]:
    """(doc_id, text): prose with shared passages, exact and near copies, nulls, empty, odd and long texts."""
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choice("abcdeéß漢") for _ in range(rng.randint(1, 6))) for _ in range(400)]
    prose = lambda k: [rng.choice(vocabulary) for _ in range(k)]
    passage, other = prose(70), prose(25)
    rows = []
    for i in range(n):
        words = prose(rng.randint(0, 120))
        if i % 4 == 0:
            at = rng.randint(0, len(words))
            words[at:at] = passage if i % 8 else other
        rows.append((i * 3, rng.choice([" ", "\n", "  "]).join(words).capitalize()))
    rows += [(1000, rows[4][1]), (1001, rows[4][1] + " more"), (1002, None), (1003, ""), (1004, " \t\n"), (1005, "one"), (1006, "one two"), (1007, " ".join(passage * 30)), (1008, "x " * 5000), (None, " ".join(other)), (1009, "\x00\x1c a b")]
    rows += [(1005, "one"), (12, "another text under a known id " + " ".join(passage))]
    return rows


def frame(spark, rows: list[tuple]):
    full = [(d, t, "en", None, None if t is None else len(t), 1, "kd", "r", 0.5, ["a"], "b", "s") for d, t in rows]
    return spark.createDataFrame(full, SCHEMA).repartition(3)
