import hashlib
import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import regex
from pyspark.sql import functions as F

from frontfill.llm import chat_format, language_id, packing, pieces_codec, quality_rules, sharding, token_counts
from frontfill.llm.units import plain, tokenizer, vocabulary_path
from tests.llm.data import WORD, awkward, frame


def base_counts(text):
    text = text or ""
    w = WORD.findall(text)
    tri = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = [False] * len(w)
    for i in range(len(w) - 2):
        if tri[tuple(w[i : i + 3])] > 1:
            hit[i : i + 3] = [True] * 3
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), dup, sum(hit)


def test_quality_measures(spark):
    labels = spark.createDataFrame([(i, i % 2) for i in range(30)], "doc_id long, quality int")
    got = quality_rules.judge(frame(spark), labels).collect()
    want = Counter()
    for r in awkward():
        c = base_counts(r[1])
        failed = c[0] < 50 or 100 * c[4] > 50 * c[0]
        want[(r[0], *c, failed)] += 1
    assert Counter((r.doc_id, *(r[m] for m in quality_rules.MEASURES), r.base_failed) for r in got) == want
    assert not any(r.kept and r.base_failed for r in got)
    assert quality_rules.judge(frame(spark, []), labels).count() == 0


def test_binomial_is_exact():
    for n, p in ((5, 0.3), (40, 0.0125), (400, 0.05)):
        pmf = [math.comb(n, k) * p**k * (1 - p) ** (n - k) for k in range(n + 1)]
        for k in (0, 1, n // 10, n // 2, n - 1):
            assert math.isclose(quality_rules.binomial_cdf(k, n, p), sum(pmf[: k + 1]), rel_tol=1e-9, abs_tol=1e-12)
    assert abs(quality_rules.binomial_cdf(3, 200, quality_rules.upper_bound(3, 200, 0.05)) - 0.05) < 1e-6


def test_quality_cutoffs_hold_their_risk(spark):
    """Good documents rejected by certified cutoffs stay under the bound; a bad group is caught."""
    rnd = random.Random(3)
    rows, labels = [], []
    for i in range(3000):
        bad = i % 3 == 0
        words = [f"w{rnd.randint(0, 9999)}" for _ in range(80)]
        if bad:
            words = [x if rnd.random() > 0.3 else "###$$$" for x in words]
        rows.append((i, " ".join(words), "en", "s", 0, 1, 2, 3, 4, "n", "s"))
        labels.append((i, int(not bad)))
    got = quality_rules.judge(frame(spark, rows), spark.createDataFrame(labels, "doc_id long, quality int")).collect()
    good = [r.kept for r in got if r.doc_id % 3]
    assert sum(good) >= 0.95 * len(good)
    assert sum(r.kept for r in got if r.doc_id % 3 == 0) < 50


def test_quality_verdict_by_definition(spark):
    """``kept`` against cutoffs found by summing binomial terms over the labelled rows."""
    rnd = random.Random(17)
    rows, labels = [], []
    for i in range(4000):
        words = [f"w{rnd.randint(0, 9999)}" if rnd.random() > (i % 7) * 0.02 else "#$%" for _ in range(rnd.randint(45, 90))]
        rows.append((i, " ".join(words), ("en", None)[i % 2], "s", 0, 1, 2, 3, 4, "n", "s"))
        labels += [(i, int(i % 7 < 5))] * (i % 5 > 0) + [(i, 0)] * (i % 211 == 0)
    got = {r.doc_id: r.kept for r in quality_rules.judge(frame(spark, rows), spark.createDataFrame(labels, "doc_id long, quality int")).collect()}
    base = {r[0]: base_counts(r[1]) for r in rows}
    failed = {i: c[0] < 50 or 100 * c[4] > 50 * c[0] for i, c in base.items()}
    scores = {i: (1000 * c[2] / max(c[1], 1), 1000 * c[3] / max(c[0], 1), 1000 * c[4] / max(c[0], 1), 10 * c[1] / max(c[0], 1)) for i, c in base.items()}
    least = {}
    for i, q in labels:
        least[i] = min(q, least.get(i, 1))
    lang = {r[0]: r[2] for r in rows}
    good = defaultdict(list)
    for i, q in least.items():
        if q == 1 and not failed[i]:
            good[lang[i]].append(i)
    cut = {}
    for g, ids in good.items():
        n, p = len(ids), quality_rules.ALPHA / 4
        for j in range(4):
            for c in quality_rules.GRID:
                k = sum(scores[i][j] > c for i in ids)
                if sum(math.comb(n, x) * p**x * (1 - p) ** (n - x) for x in range(k + 1)) > quality_rules.DELTA / (len(good) * 4):
                    break
                cut[g, j] = c
    assert cut and got == {i: not failed[i] and not any(scores[i][j] > cut.get((lang[i], j), math.inf) for j in range(4)) for i in got}


def test_token_counts_are_the_librarys(spark):
    tok = tokenizer(token_counts.VOCABULARY)
    got = token_counts.count_tokens(frame(spark)).collect()
    want = Counter((r[0], len((r[1] or "").encode()), len(tok.encode(r[1] or "", add_special_tokens=False))) for r in awkward())
    assert Counter((r.doc_id, r.n_bytes, r.n_tokens) for r in got) == want
    assert all(r.over_limit == (r.n_tokens > 512) for r in got)
    assert token_counts.count_tokens(frame(spark, [])).count() == 0


def test_safe_cut_agrees_with_the_library():
    from frontfill.llm.units import BYTE_UNITS, WORD_UNITS

    byte, word = tokenizer("byte_bpe_50k.json"), tokenizer("word_bpe_49k.json")
    rnd = random.Random(11)
    chars = [chr(i) for i in range(32, 127)] + ["\n", "\t", "\r"] * 4 + [" "] * 30 + [chr(i) for i in range(0xA1, 0x180)] + list("–—‘’“”…'") + ["'s", "'LL", "ǅ", "ß"]
    for _ in range(400):
        t = "".join(rnd.choice(chars) for _ in range(rnd.randint(1, 60)))
        if not plain(t):
            continue
        a = [i for u in BYTE_UNITS.findall(t) for i in byte.encode(u, add_special_tokens=False).ids]
        assert a == byte.encode(t, add_special_tokens=False).ids, repr(t)
        b = [i for u in WORD_UNITS.findall(t.lower()) for i in word.encode(u, add_special_tokens=False).ids]
        assert b == word.encode(t, add_special_tokens=False).ids, repr(t)


@pytest.mark.parametrize("copies", [1, 40])
def test_sharding(spark, copies):
    rows = [r for r in awkward() for _ in range(copies)]
    got = sharding.shard_rows(frame(spark, rows)).collect()
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter((r[0], len((r[1] or "").encode()) + 1, zlib.crc32((r[1] or "").encode())) for r in rows)
    by = defaultdict(list)
    for r in got:
        by[r.shard].append(r.slot)
    assert set(by) <= set(range(16))
    counts = [len(by[s]) for s in range(16)]
    assert max(counts) - min(counts) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in by.values())
    assert sharding.shard_rows(frame(spark, [])).count() == 0


def test_sharding_moves_little_when_rows_come():
    """Rows stay with their ring owner but for the overflow."""
    rnd = random.Random(1)
    counts = Counter(rnd.randrange(16_384) for _ in range(50_000))
    owner = sharding.ring(16, 64, 16_384)
    runs = sharding.plan(dict(counts))
    home = sum(hi - lo for k, lo, hi, s, _ in runs if owner[k] == s)
    loads = Counter(owner[k] for k, n in counts.items() for _ in range(n))
    overflow = sum(max(0, n - 50_000 // 16) for n in loads.values())
    assert 50_000 - home <= overflow + 16
    order = sharding.clockwise(owner, 16)
    assert all(order[k][0] == owner[k] and sorted(order[k]) == list(range(16)) for k in range(0, 16_384, 97))
    assert order[16_383] == list(dict.fromkeys([owner[16_383], *owner]))


TURNS = [
    (1, 0, "system", "be <|kind|> \\ and <\\| brief"), (1, 1, "user", "hi"), (1, 2, "assistant", "hello <|end|>"), (1, 3, "user", None), (1, 4, "assistant", ""),
    (6, 0, "system", "rules of the talk"), *((6, 1 + i, ("user", "assistant")[i % 2], f"say {i} " * (1 + 3 * i)) for i in range(20)),
    (2, 0, "user", "long " * 300), (2, 1, "assistant", "reply " * 500), (2, 2, "user", "é" * 10), (2, 3, "assistant", "done\\"), (3, 0, "assistant", "alone"),
    (4, None, None, "x"), (4, 1, "assistant", "a"), (4, 1, "assistant", "a"), (4, 1, "assistant", "b\nc"), (None, 0, "assistant", "no id"),
    *((5, i, ("user", "assistant")[i % 2], f"turn {i} " * 30) for i in range(60)), (-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]"),
]


def turn_tokens(text):
    return 3 + len(regex.findall(r"\p{L}{1,4}|\p{N}{1,3}|[^\x09-\x0D\x20\p{L}\p{N}]", text))


def plain_windows(turns, budget, history, history_budget):
    """(first turn, first repeated turn, end, tokens shown) of each window, by definition."""
    cost, out, lo = [turn_tokens(x) for _, x in turns], [], 0
    while lo < len(turns):
        back, base = lo, 0
        for k in range(history + 1 if lo else 0):
            past = sum(cost[lo - k : lo])
            both = past + (cost[0] if turns[0][0] == "system" and lo > k else 0)
            if k <= lo and (k == 0 or (past <= history_budget and both + cost[lo] <= budget)):
                back, base = lo - k, both
        hi, shown = lo + 1, base + cost[lo]
        while hi < len(turns) and shown + cost[hi] <= budget:
            shown += cost[hi]
            hi += 1
        out.append((lo, back, hi, shown))
        lo = hi
    return out


@pytest.mark.parametrize("budget", [40, 512, 10_000])
def test_chat_round_trip(spark, budget):
    df = spark.createDataFrame([(*t, 9) for t in TURNS], "conv_id long, turn long, role string, text string, window int")
    out = chat_format.windows(df, budget=budget, history=2, history_budget=60)
    back = {r.conv_id: r for r in chat_format.read_back(out).collect()}
    conv = defaultdict(list)
    for c, t, role, text in TURNS:
        conv[c].append((-1 if t is None else t, role or "", text or ""))
    assert set(back) == set(conv)
    lens, shown = defaultdict(int), defaultdict(list)
    for r in out.orderBy("conv_id", "window").collect():
        lens[r.conv_id] += len(r.formatted)
        shown[r.conv_id].append((r.first_turn, r.first_turn + r.n_turns, r.formatted.count(chat_format.AGAIN)))
    for c, turns in conv.items():
        turns = [(r, x) for _, r, x in sorted(turns)]
        assert [tuple(x) for x in back[c].turns] == turns
        assert back[c].loss_text == "".join(x for r, x in turns if r == "assistant")
        want = plain_windows(turns, budget, 2, 60)
        assert shown[c] == [(lo, hi, lo - at + (turns[0][0] == "system" and at > 0)) for lo, at, hi, _ in want]
        system = turn_tokens(turns[0][1]) if turns[0][0] == "system" else 0
        assert all(n <= budget or (hi == lo + 1 and turn_tokens(turns[lo][1]) + system > budget) for lo, _, hi, n in want)
    assert {c: back[c].formatted_chars for c in back} == lens


def test_chat_repeats_are_masked(spark):
    out = chat_format.windows(spark.createDataFrame([t for t in TURNS if t[0] in (1, 5)], "conv_id long, turn long, role string, text string"), budget=200, history=2, history_budget=200).where("conv_id = 5").orderBy("window").collect()
    assert len(out) > 3
    assert all(r.formatted.count(chat_format.AGAIN) == (0 if r.window == 0 else 2) for r in out)
    assert sum(len(r.loss) for r in out) == 30


def test_packing(spark):
    tok = tokenizer(packing.VOCABULARY)
    got = packing.pack_documents(frame(spark), length=256, with_ids=True, group_bytes=30_000).collect()
    want = {r[0]: tok.encode(r[1] or "", add_special_tokens=False).ids + [1] for r in awkward()}
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append(r)
        ids = want[r.doc_id][r.start : r.start + r.length]
        assert r.ids_crc32 == zlib.crc32(np.array(ids, "<u4").tobytes()) and r.doc_tokens == len(want[r.doc_id])
        assert np.frombuffer(r.ids, "<u4").tolist() == ids
    for d, ids in want.items():
        n = sum(1 for r in awkward() if r[0] == d)
        assert sum(r.length for r in by_doc[d]) == n * len(ids)
    for rs in by_seq.values():
        at = 0
        for r in sorted(rs, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 256
    assert packing.pack_documents(frame(spark, [])).count() == 0


def test_packing_spreads_repeated_rows(spark):
    """Neither null identifiers nor a row that repeats fill one group."""
    rows = [(None, f"text {i} " * 30, "en", "s", 0, 1, 2, 3, 4, "n", "s") for i in range(300)] + [(7, "same " * 40, "en", "s", 0, 1, 2, 3, 4, "n", "s")] * 300
    got = packing.pack_documents(frame(spark, rows), group_bytes=12_000).collect()
    groups = Counter(r.sequence_id >> 32 for r in got)
    assert len(got) == 600 and len(groups) > 5 and max(groups.values()) < 300


def test_frequent_units_cover_all_documents(spark):
    rows = [(i, f" common unit{i % 50} rare{i}", "en", "s", 0, 1, 2, 3, 4, "n", "s") for i in range(400)]
    got = token_counts.frequent_units(frame(spark, rows), table_size=60)
    assert {" common", " unit", " rare"} <= set(got) and len(got) <= 60


def test_first_fit_is_the_plain_one():
    rnd = random.Random(2)
    for _ in range(30):
        sizes = sorted((rnd.randint(1, 64) for _ in range(rnd.randint(1, 120))), reverse=True)
        free, want = [], []
        for s in sizes:
            k = next((i for i, f in enumerate(free) if f >= s), len(free))
            if k == len(free):
                free.append(64)
            want.append((k, 64 - free[k]))
            free[k] -= s
        bins, offs = packing.first_fit_decreasing(np.array(sizes), 64)
        assert list(zip(bins.tolist(), offs.tolist(), strict=True)) == want


def plain_phrases(parser, k, sample, text):
    """Cross-parse by definition: the longest prefix of the rest that occurs in the sample, or one symbol that it lacks."""
    s = bytes(parser.symbols(sample)[k].tolist())
    found = lacked = 0
    for lo in range(0, len(text), language_id.BLOCK):
        t = bytes(parser.symbols(text[lo : lo + language_id.BLOCK])[k].tolist())
        at = 0
        while at < len(t):
            n = 0
            while at + n < len(t) and t[at : at + n + 1] in s:
                n += 1
            found, lacked = found + (n > 0), lacked + (n == 0)
            at += max(n, 1)
    return found, lacked


def test_cross_parsing_by_definition():
    rnd = random.Random(4)
    samples = {k: "".join(rnd.choice(v) for _ in range(2000)) for k, v in {"aa": "abc de", "bb": "bcd ef", "cc": "xyz ab\n"}.items()}
    p = language_id.CrossParser(samples)
    texts = ["".join(rnd.choice("abcdefxyz Q1ß") for _ in range(rnd.randint(0, 1500))) for _ in range(12)] + ["", "q", samples["aa"][:700]]
    found, lacked = p.phrases(texts)
    for i, t in enumerate(texts):
        for k, name in enumerate(p.names):
            assert (found[i, k], lacked[i, k]) == plain_phrases(p, k, samples[name], t)


def test_short_samples_do_not_win():
    rnd = random.Random(8)
    words = {"one": [f"{a}{b}" for a in ("ta", "ren", "ol") for b in ("mi", "sa", "tur")], "two": [f"{a}{b}" for a in ("kra", "vum", "zip") for b in ("ek", "oj", "ub")]}
    say = lambda k, n: " ".join(rnd.choice(words[k]) for _ in range(n))
    samples = {k: say(k, 4000) for k in words}
    texts = [say(k, 40) for k in words for _ in range(5)]
    for extra in ("", "a", "ok", "a e i o u t n s r " * 8, say("two", 4)):
        tags, scores = language_id.CrossParser(samples | {"few": extra}).judge(texts)
        assert tags == ["one"] * 5 + ["two"] * 5 and all(0 <= x <= 1 for x in scores)


def test_scripts_tell_languages_apart():
    rnd = random.Random(9)
    ranges = {"ja": [(0x3041, 0x3096), (0x4E00, 0x4E80)], "zh": [(0x4E00, 0x5400)], "ru": [(0x430, 0x44F)], "el": [(0x3B1, 0x3C9)], "ko": [(0xAC00, 0xB000)]}
    every = {k: [chr(c) for lo, hi in v for c in range(lo, hi + 1)] for k, v in ranges.items()}
    say = lambda k, n: "".join(rnd.choice(every[k]) if rnd.random() < 0.8 else " " for _ in range(n))
    p = language_id.CrossParser({k: say(k, 3000) for k in every})
    for k in every:
        assert p.judge([say(k, 300) for _ in range(5)])[0] == [k] * 5


def test_sample_counts_copies_once(spark):
    rows = [(i, "the same text " * 30, "en", "s", 0, 1, 2, 3, 4, "n", "s") for i in range(300)] + [(1000 + i, f"{chr(97 + i % 26)}ord{i} " * 40, "en", "s", 0, 1, 2, 3, 4, "n", "s") for i in range(60)]
    sample = language_id.training_samples(frame(spark, rows), F.lit(True), sample_docs=40)["en"]
    assert sample.count("\n") == 39 and sample.count("same") < 30


def test_language_id(spark, small):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    samples = language_id.training_samples(docs, ~language_id.held_out())
    out = language_id.identify(docs.select("doc_id", "text", F.col("lang").alias("truth")), samples).where(language_id.held_out()).collect()
    assert sum(r.truth == r.lang_pred for r in out) >= 0.99 * len(out)
    got = language_id.identify(frame(spark), samples).collect()
    assert len(got) == len(awkward())
    for r in got:
        assert (r.lang_pred == "und") == (not any(c.isalpha() for c in r.text or "")) and 0 <= r.score <= 1
    assert {r.lang_pred for r in language_id.identify(frame(spark), {}).collect()} == {"und"}
    clash = language_id.identify(frame(spark).withColumnsRenamed({"rank": "score", "lang": "lang_pred"}), samples).collect()
    assert Counter((r.doc_id, r.lang_pred) for r in clash) == Counter((r.doc_id, r.lang_pred) for r in got)
    assert language_id.training_samples(frame(spark, []), F.lit(True)) == {}
    assert language_id.identify(frame(spark, []), samples).count() == 0


def test_pieces_are_the_librarys(spark):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=vocabulary_path(pieces_codec.VOCABULARY))
    got = {r.doc_id: r for r in pieces_codec.encode_documents(frame(spark)).collect()}
    for r in awkward():
        assert got[r[0]].ids == lib.encode(r[1] or "")
        assert got[r[0]].round_trip == ("▁" not in (r[1] or ""))
    back = {r.doc_id: r.text for r in pieces_codec.decode_documents(spark.createDataFrame([(i, r.ids) for i, r in got.items()], "doc_id long, ids array<int>")).collect()}
    assert all(back[r[0]] == (r[1] or "") for r in awkward() if "▁" not in (r[1] or ""))
    m = pieces_codec.model()
    rnd = random.Random(6)
    chars = [chr(c) for c in range(32, 127)] + list(" " * 30 + "\n\t") + [chr(c) for c in range(0xA0, 0x250)] + list("日本語テ한국어абв▁🙂")
    for t in ["".join(rnd.choice(chars) for _ in range(rnd.randint(0, 60))) for _ in range(500)] + ["".join(rnd.choice("aeitn s") for _ in range(60)) for _ in range(500)] + [" " * k + "x" for k in range(40)]:
        assert np.frombuffer(m.encode(t), np.uint32).tolist() == lib.encode(t)
    assert pieces_codec.encode_documents(frame(spark, [])).count() == 0


def test_pieces_of_a_unigram_model_take_the_best_path():
    rnd = random.Random(12)
    mark = pieces_codec.MARK
    words = sorted({"".join(rnd.choice("abcd" + mark) for _ in range(rnd.randint(2, 5))) for _ in range(120)})
    pieces = [f"<0x{b:02X}>" for b in range(256)] + [*"abc", mark, *(w for w in words if mark not in w[1:])]
    score = [0.0] * 256 + [-rnd.uniform(1, 9) for _ in pieces[256:]]
    m = pieces_codec.PieceModel(pieces, score, list(range(256)), [i >= 256 for i in range(len(pieces))])
    by = {p: i for i, p in enumerate(pieces) if i >= 256}
    for text in ["".join(rnd.choice("abc dé") for _ in range(rnd.randint(1, 40))) for _ in range(200)]:
        t = mark + text.replace(" ", mark)
        best = [0.0] + [-1e18] * len(t)
        for e in range(1, len(t) + 1):
            best[e] = max([best[e - 1] + pieces_codec.LOW] + [best[s] + score[by[t[s:e]]] for s in range(max(0, e - 6), e) if t[s:e] in by])
        ids = np.frombuffer(m.encode(text), np.uint32).tolist()
        low = sum(c not in m.id_of for c in t) if not any("d" in p for p in by) else None
        total = sum(score[i] for i in ids if i >= 256)
        bytes_ = bytes(i for i in ids if i < 256).decode()
        assert math.isclose(total + pieces_codec.LOW * len(bytes_), best[-1], rel_tol=1e-9) and low in (None, len(bytes_))
        assert m.decode(ids) == text


def test_digests_match_hashlib(spark):
    import __spark_entry__ as e

    got = {r.conv_id: r for r in e.queries()["op6_chat_format"](spark, "/root/testdata/sf0.001").collect()}
    say = "</s>[INST] ok [/INST]"
    assert got[-7].n_turns == 2 and got[-7].loss_chars == len(say) and got[-7].loss_sha256 == hashlib.sha256(say.encode()).hexdigest()
    assert got[-7].turns_sha256 == hashlib.sha256(f"user\n{say}\nassistant\n{say}\n".encode()).hexdigest()
