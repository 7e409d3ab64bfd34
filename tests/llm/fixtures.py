"""Small tables with the awkward cases: nulls, empty texts, repeats, ties, extra columns with clashing names."""

import random


def documents(spark, n=60, seed=1, extra=True):
    rnd = random.Random(seed)
    words = ["the", "of", "Idiot", "straße", "été", "x1", "and", "to", "a", "running", "ñandú", "low"]
    texts = [" ".join(rnd.choice(words) for _ in range(rnd.randrange(0, 40))) for _ in range(n // 2)]
    texts += [None, "", "   ", "\n\t", "word " * 3000, "a" * 5000, texts[3], texts[3], texts[5] + " more", "日本語 テキスト", "été İstanbul ΣΑΣ", "tab\tand\x0bvt\x1cfs nbsp"]
    texts += [rnd.choice(texts[:10]) for _ in range(n - len(texts))]
    rows = [(i, t, "en", f"s{i % 3}", len(t or ""), "clash", 7) for i, t in enumerate(texts)]
    rows += [rows[4], rows[4], (None, "no id", None, None, None, None, None)]
    rnd.shuffle(rows)
    kind = "doc_id bigint, text string, lang string, source string, n_chars bigint, fingerprint string, kept int"
    df = spark.createDataFrame(rows, kind)
    return df if extra else df.drop("fingerprint", "kept")


def empty(spark):
    return spark.createDataFrame([], "doc_id bigint, text string, lang string, source string, n_chars bigint")
