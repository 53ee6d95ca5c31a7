"""A small corpus with planted cases."""

import numpy as np

INSULTS = ["trash", "idiot", "moron", "scum"]


def prose(seed, n):
    rng = np.random.default_rng(seed)
    return " ".join("".join(rng.choice(list("abcdefghij"), 5)) for _ in range(n))


def corpus(spark, path):
    rows = [(i, prose(i, 80), "en", f"s{i % 4}", 1, 0) for i in range(60)]
    for i in range(100, 160):
        rows.append((i, f"{prose(i, 30)} you {INSULTS[i % 4]} and {INSULTS[(i + 1) % 4]}. {prose(i + 500, 30)}", "en", "s1", 1, 0))
    near = prose(1000, 100).split()
    for k in range(4):
        words = list(near)
        words[10 * k : 10 * k + 1] = [f"changed{k}"]
        rows.append((200 + k, " ".join(words), "en", "s2", 1, 0))
    item = prose(2000, 30)
    rows += [(300, f"{prose(3000, 40)} {item} {prose(3001, 40)}", "en", "s3", 1, 0), (301, item, "en", "s3", 1, 0), (400, f"{prose(4000, 60)} 4111111111111111", "en", None, 1, 0), (401, None, None, None, None, None), (None, prose(4002, 70), "en", "s0", 1, 0)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row int").write.parquet(f"{path}/sf/documents.parquet")
    spark.createDataFrame([(i, 1, int(100 <= i < 160)) for i in [*range(60), *range(120, 160)]], "doc_id long, quality int, toxic int").write.parquet(f"{path}/sf/labels.parquet")
    spark.createDataFrame([(1, item), (2, None)], "item_id long, text string").write.parquet(f"{path}/sf/benchmark.parquet")
    return f"{path}/sf"
