import random
import re

from balclust.llm import repetition


def brute(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    chars = sum(map(len, words))
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]

    def covered(n, earlier):
        grams, first, inside = [tuple(words[k : k + n]) for k in range(len(words) - n + 1)], {}, set()
        for k, g in enumerate(grams):
            if earlier and g in first or not earlier and grams.count(g) > 1:
                inside.update(range(k, k + n))
            first.setdefault(g, k)
        return inside

    seen, dup_lines, dup_chars = set(), 0, 0
    for x in lines:
        if x in seen:
            dup_lines += 1
            dup_chars += len(x)
        seen.add(x)
    repeat = len(covered(8, False))
    failed = len(words) < 20 or 100 * repeat > 30 * len(words)
    dup = [sum(len(words[k]) for k in covered(n, True)) for n in (5, 7, 10)]
    kept = not failed and 100 * dup_chars <= 20 * chars and all(100 * d <= limit * chars for d, limit in zip(dup, (15, 13, 10)))
    return len(words), chars, len(re.findall(r"[#*$%&|<>]", text)), dup_lines, repeat, *dup, failed, kept


def test_equals_brute_force(spark, tmp_path):
    rng = random.Random(5)
    texts = [None, "", " \n\t", "one", "a b c\n\na b c\n a b c\r\na b c", "é#| ünï <&>\n" * 3, "x " * 25, "end\n" * 30, "same same\n"]
    for size in (19, 20, 40, 90, 200):
        for vocabulary in (2, 6, 60, 500):
            texts.append("".join(f"w{rng.randrange(vocabulary)}é{rng.choice([' ', '  ', chr(10), chr(9)])}" for _ in range(size)))
    texts.append(" ".join(f"u{k}" for k in range(50)) + "\n" + " ".join(f"u{k}" for k in range(12)))
    texts += texts[5:8]
    spark.createDataFrame([(k, t, 1) for k, t in enumerate(texts)], "doc_id long, text string, kept int").repartition(2).write.parquet(str(tmp_path / "documents.parquet"))
    got = {r.doc_id: tuple(r[c] for c in ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "dup_chars_5", "dup_chars_7", "dup_chars_10", "base_failed", "kept"]) for r in repetition.op2(spark, str(tmp_path)).collect()}
    assert got == {k: brute(t) for k, t in enumerate(texts)}


def test_long_text_and_empty_table(spark):
    df = spark.createDataFrame([(1, " ".join(str(k) for k in range(400_000)))], "doc_id long, text string")
    (row,) = repetition.assess(df).collect()
    assert row.n_words == 400_000 and row.kept and row.n_repeat_words == 0
    assert repetition.assess(df.limit(0)).count() == 0
