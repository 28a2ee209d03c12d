"""The stages of the pipeline that reject rows, against brute force, on rows whose identifiers repeat or are null."""

import unicodedata
from collections import Counter, defaultdict

import corpus_pipeline
from tests.llm.data import awkward, frame
from tests.llm.test_dedup import SPACE, brute_classes, brute_windows


def say(word, n):
    return " ".join(f"{word}{i}" for i in range(n))


def row(doc_id, text):
    return (doc_id, text, "en", "s", 0, 1, 2, 3, 4, "n", "s")


def order(r):
    return (r[0] is None, r[0] or 0)


def brute_exact(rows):
    groups = defaultdict(list)
    for r in rows:
        groups[SPACE.sub("", r[1] or "")].append(r)
    return [min(g, key=lambda r: (-len(r[1] or ""), *order(r))) for g in groups.values()]


def brute_near(rows):
    """Each row is a document of its own, whatever its identifier."""
    classes = defaultdict(list)
    for i, (_, root) in brute_classes([(i, *r[1:]) for i, r in enumerate(rows)], 5).items():
        classes[root].append(rows[i])
    # rows of equal identifiers stay in the order of the table
    return [min(c, key=order) for c in classes.values()]


def brute_passages(rows):
    left = Counter()
    for (i, n_words, n_removed, text), n in brute_windows(rows, 50).items():
        if not n_removed or n_removed < n_words:
            left[(i, text)] += n
    return left


def staged(spark, rows):
    """What the stages before packing leave: identifier and words."""
    docs = frame(spark, rows)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.checkpointed(stage(spark, docs, None))
    return Counter((r.doc_id, " ".join(SPACE.split((r.text or "").strip(" \t\n\x0b\x0c\r")))) for r in docs.collect())


def expected(rows):
    spoken = [r for r in rows if any(unicodedata.category(c)[0] == "L" for c in r[1] or "")]
    return brute_passages(brute_near(brute_exact(spoken)))


def repeated():
    long, changed = say("k", 80), say("m", 90)
    return [
        row(900, long), row(900, long),  # a whole row twice, longer than the passage window
        row(901, say("p", 9)), row(901, say("p", 9)), row(901, say("p", 9)),
        row(902, say("q", 70)), row(902, say("r", 70)), row(903, say("q", 70)), row(850, say("r", 70)),  # an identifier with a rejected and a kept text
        row(910, changed), row(910, changed + " tail"), row(909, say("t", 60)),
    ]


def test_repeated_rows_leave_one(spark):
    rows = awkward() + repeated()
    got = staged(spark, rows)
    assert got == expected(rows)
    assert got[(900, say("k", 80))] == 1 and got[(901, say("p", 9))] == 1


def test_stages_alone_number_their_rows(spark):
    rows = repeated()
    exact = corpus_pipeline.exact_stage(spark, frame(spark, rows), None)
    assert Counter((r.doc_id, r.text) for r in exact.collect()) == Counter((r[0], r[1]) for r in brute_exact(rows))
    near = corpus_pipeline.near_stage(spark, frame(spark, brute_exact(rows)), None)
    assert Counter((r.doc_id, r.text) for r in near.collect()) == Counter((r[0], r[1]) for r in brute_near(brute_exact(rows)))


def test_null_identifiers_follow_their_own_verdict(spark):
    clean, copy, near = say("a", 40), say("b", 45), say("c", 100)
    rows = [
        row(None, clean), row(None, copy), row(800, copy), row(None, near), row(None, near + " tail"), row(None, say("d", 70)), row(None, say("d", 70)),
        row(801, say("e", 30)), row(None, "12 34"), row(None, None),
    ]
    got = staged(spark, rows)
    assert got == expected(rows)
    assert sorted(t for i, t in got if i is None) == sorted([clean, near, say("d", 70)])
    assert got[(800, copy)] == 1
