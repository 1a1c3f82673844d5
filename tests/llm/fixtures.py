"""Small document tables with every awkward case, and brute-force twins."""

import hashlib
import random
import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


def words(text):
    return WORD.findall(text or "")


def sha(data):
    return hashlib.sha256(data if isinstance(data, bytes) else data.encode()).hexdigest()


def documents(seed=1, n=60):
    """Prose, exact and near copies, shared passages, repeated lines and rows, nulls, blanks, one very long text."""
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choice("abcdeéß") for _ in range(rng.randrange(1, 7))) for _ in range(300)] + ["the", "of", "and", "A.", "#x"]
    prose = lambda k: " ".join(rng.choice(vocabulary) for _ in range(k))
    passage, texts = prose(90), []
    for i in range(n):
        kind = i % 6
        if kind == 1 and texts:
            texts.append(texts[i - 1])
        elif kind == 2 and texts:
            near = words(texts[i - 2])
            near[len(near) // 2] = "edited"
            texts.append(" ".join(near))
        elif kind == 3:
            texts.append(prose(40) + "\n" + passage + " \t" + prose(30))
        else:
            texts.append(prose(rng.randrange(60, 200)))
    texts += [None, "", "  \t\n ", "one", "one two", "two  one", "same line\nsame line\n\nsame line", "ab " * 120, "z" * 500, prose(4000)]
    rows = [(i, t, "en", None if i % 7 == 0 else f"src{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    rows.append(rows[3])
    rows.append((None, texts[5], None, None, None))
    return rows


def frame(spark, rows=None):
    """The rows with extra columns whose names clash with inner ones."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame(documents() if rows is None else rows, COLUMNS)
    return df.withColumns({"h": F.lit("x"), "_id": F.lit(1), "marks": F.lit(2), "key": F.lit(3), "size": F.lit(4)})
