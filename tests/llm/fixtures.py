"""Small corpora with the awkward cases: nulls, empty and long texts, ties, repeats, clashing columns."""

from __future__ import annotations

import random

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _key string, tokens int"
EN = "the of and thing that with there where from this other and only under about".split()
FR = "le la les que dans pour avec mais sous une des être après élève où".split()


def words(rng: random.Random, pool: list[str], n: int) -> str:
    return " ".join(rng.choice(pool) + rng.choice(["", "s", "ed", "ing", "on"]) for _ in range(n))


def documents(seed: int = 5) -> list[tuple]:
    rng = random.Random(seed)
    shared = "This line is shared by a good many of the documents here, more or less"
    out, texts = [], []
    for i in range(60):
        pool = FR if i % 4 == 0 else EN
        lines = [words(rng, pool, rng.randint(5, 40)) for _ in range(rng.randint(1, 4))]
        if i % 5 == 0:
            lines.insert(1, f"  {shared.upper()}\t")
        if i % 7 == 0:
            lines.append(shared)
        texts.append("\n".join(lines))
    texts += [texts[3]] * 4  # exact copies
    for k in range(5):  # near copies
        w = texts[8].split(" ")
        w[k] = "changed"
        texts.append(" ".join(w))
    texts += ["", None, " \n\t\n", "…!?", "a", "one two three", "one two three", "ONE  two\tthree", "x" * 5000, "word " * 3000, "\n".join([shared] * 3), "naïve café <|endoftext|> 漢字 🙂 ½\x1f end  "]
    for i, t in enumerate(texts):
        out.append((i, t, "fr" if i < 60 and i % 4 == 0 else "en", f"src{i % 3}", len(t) if t is not None else None, "clash", i))
    out += [out[10], out[10]]  # repeated rows
    return out


def frame(spark, rows=None, parts: int = 3):
    return spark.createDataFrame(documents() if rows is None else rows, SCHEMA).repartition(parts)
