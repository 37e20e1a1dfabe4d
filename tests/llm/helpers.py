"""Small messy tables and brute-force versions of the operators."""

import re

UPPER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def docs(spark, texts, extra=()):
    """Documents with columns whose names operators might use inside."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(i, t, "en", "src0", len(t or "")) for i, t in texts], DOCS)
    for name in ("node", "bucket", "_text", "words", "body", "h", "_rep", "_p", "_copy", "rank", "text_", *extra):
        df = df.withColumn(name, F.lit("clash"))
    return df


def words_of(text):
    return re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(UPPER))


def shingles(text):
    w = words_of(text)
    return set() if not w else {tuple(w)} if len(w) < 5 else {tuple(w[k : k + 5]) for k in range(len(w) - 4)}


def groups(ids, linked):
    """Smallest id reachable, by brute force over all pairs."""
    up = {i: i for i in ids}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and linked(a, b):
                x, y = top(a), top(b)
                up[max(x, y)] = min(x, y)
    return {i: top(i) for i in ids}
