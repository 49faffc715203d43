"""Small corpora with every odd case, and brute-force versions."""

import random
import re

GRAPHIC = re.compile("[^\x20\x09-\x0d]+")
ALNUM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def corpus(n=120, seed=1, words=40, longest=300):
    """Texts over few words, so that passages repeat; with copies, nulls, empty texts, odd spaces and a long one."""
    r = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(words)] + ["Été", "naïve", "ÄÖ", "x.y"]
    passages = [" ".join(r.choices(vocabulary, k=35)) for _ in range(4)]
    out = []
    for i in range(n):
        parts = []
        for _ in range(r.randint(1, 4)):
            parts.append(r.choice(passages) if r.random() < 0.3 else " ".join(r.choices(vocabulary, k=r.randint(1, longest // 8))))
        out.append((i * 3, r.choice(["\n", " ", "\t \n"]).join(parts), r.choice(["en", "fr"]), "src0", 0))
    out += [(1000, None, None, None, None), (1001, "", "en", "src1", 0), (1002, " \n\t ", "en", "src1", 3), (1003, out[5][1], "en", "src1", 0), (1004, out[5][1], "fr", "src1", 0), (1005, "w1 w2", "en", "src1", 5), (1006, " ".join(r.choices(vocabulary, k=20000)), "en", "src2", 0), (None, passages[0], "en", "src1", 0)]
    return out


def frame(spark, rows, parts=5):
    return spark.createDataFrame(rows, SCHEMA).repartition(parts)


def with_clashes(df):
    """Extra columns named as the operators' own."""
    from pyspark.sql import functions as F

    for c in ("node", "id", "key", "size", "score", "shard", "slot", "rank", "spans", "toxic", "_copies", "_rate", "held_out", "class_id", "bands", "root", "copies", "_h", "n"):
        df = df.withColumn(c, F.lit(1))
    return df
