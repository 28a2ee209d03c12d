"""A small table with every awkward case: nulls, ties, repeats, long texts, clashing columns."""

import random
import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, rank int, chunk int, bucket int, size long, norm string, stratum string"


def awkward():
    rnd = random.Random(5)
    vocab = [a + b for a in ("ta", "re", "on", "li", "me", "su") for b in ("n", "r", "s", "ti", "lo", "")]
    say = lambda n: " ".join(rnd.choice(vocab) for _ in range(n))
    passage = say(60)
    base = say(120)
    near = base.split()
    near[50] = "changed"
    texts = [
        None, "", "   \n\t ", "one", "one two", "One Two", base, base, base.replace(" ", "\n"), " ".join(near), base + " tail",
        f"{say(30)} {passage} {say(20)}", f"{say(10)}\n{passage}\n\n{say(40)}", say(9000), "x" * 5000, "# $ % & | < > *" * 40,
        "same line\nsame line\nother\nsame line\n\n\n", "12 34 56 !!! ...", "日本語 テキスト です", "naïve café – “quote” …   é İstanbul ſ",
        "a <|endoftext|> b <|turn|> c", "tab\tsep\x0bvt\x0cff\rcr", "don't can't we'll THEY'RE i'm", " lead and trail ", passage + " " + passage, "▁mark ▁",
        *(say(rnd.randint(1, 200)) for _ in range(20)),
    ]
    langs = ["en", "fr", None, "en"]
    rows = [(i, t, langs[i % 4], f"s{i % 3}", 0, 1, 2, 3, 4, "n", "s") for i, t in enumerate(texts)]
    rows.append(rows[6])  # a repeated row
    return rows


def frame(spark, rows=None):
    return spark.createDataFrame(awkward() if rows is None else rows, SCHEMA)
