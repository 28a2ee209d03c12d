import hashlib
import re
from collections import Counter, defaultdict

import pyarrow as pa
import pytest

from frontfill.llm import exact_dedup, minhash_dedup, quality_rules, substring_dedup, wordscan
from frontfill.llm.graph import components
from tests.llm.data import WORD, awkward, frame

SPACE = re.compile(r"[\x20\x09-\x0D]+")


def test_exact(spark):
    rows = awkward()
    got = exact_dedup.exact_duplicates(frame(spark)).collect()
    groups = defaultdict(list)
    for r in rows:
        groups[SPACE.sub("", r[1] or "")].append((-len(r[1] or ""), r[0]))
    want = Counter()
    for r in rows:
        n = SPACE.sub("", r[1] or "")
        keep = min(groups[n])[1]
        want[(r[0], keep, len(groups[n]), r[0] == keep, hashlib.sha256(n.encode()).hexdigest())] += 1
    assert Counter(map(tuple, got)) == want
    assert exact_dedup.exact_duplicates(frame(spark, [])).count() == 0


def brute_windows(rows, n):
    words = [WORD.findall(r[1] or "") for r in rows]
    seen = Counter(tuple(w[i : i + n]) for w in words for i in range(len(w) - n + 1))
    out = Counter()
    for r, w in zip(rows, words, strict=True):
        gone = [False] * len(w)
        for i in range(len(w) - n + 1):
            if seen[tuple(w[i : i + n])] > 1:
                gone[i : i + n] = [True] * n
        out[(r[0], len(w), sum(gone), " ".join(x for x, g in zip(w, gone, strict=True) if not g))] += 1
    return out


@pytest.mark.parametrize("window,base", [(35, None), (50, None), (7, 1), (1, 1), (8, 8)])
def test_substring(spark, window, base):
    got = substring_dedup.remove_repeated(frame(spark), window=window, base=base, layout="spaces", chunk_bytes=3000).collect()
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.text or "") for r in got) == brute_windows(awkward(), window)


def test_substring_original_layout(spark):
    got = substring_dedup.remove_repeated(frame(spark), window=35, layout="original").collect()
    rows = {r[0]: r for r in awkward()}
    want = {k[0]: k for k in brute_windows(awkward(), 35)}
    for r in got:
        assert WORD.findall(r.text or "") == WORD.findall(want[r.doc_id][3])
        if not r.n_removed:
            assert r.text == rows[r.doc_id][1]
    assert substring_dedup.remove_repeated(frame(spark, [])).count() == 0


def brute_classes(rows, n, percent=80):
    low = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
    sets = defaultdict(set)
    for r in rows:
        w = WORD.findall((r[1] or "").translate(low))
        sets[r[0]] |= {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                k = len(sets[a] & sets[b])
                if 100 * k >= percent * (len(sets[a]) + len(sets[b]) - k):
                    x, y = sorted((find(a), find(b)))
                    root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("n,unit", [(4, 4 << 20), (5, 4 << 20), (4, 900)])
def test_minhash(spark, n, unit):
    want = brute_classes(awkward(), n)
    got = minhash_dedup.near_duplicates(frame(spark), shingle=n, unit_bytes=unit).collect()
    assert len(got) == len(awkward())
    assert all(want[r.doc_id] == (r.n_shingles, r.component_id) and r.kept == (r.doc_id == r.component_id) for r in got)
    assert minhash_dedup.near_duplicates(frame(spark, [])).count() == 0


@pytest.mark.parametrize("unit", [4 << 20, 4000])
def test_minhash_chains(spark, unit):
    """Copies that are each near the base but not near one another."""
    base = [f"w{i}" for i in range(300)]
    rows = []
    for k in range(12):
        w = list(base)
        for j in range(9):
            w[(k * 24 + j * 2) % 300] = f"x{k}_{j}"
        rows.append((k if k else 100, " ".join(w), "en", "s", 0, 1, 2, 3, 4, "n", "s"))
    rows.append((50, " ".join(base), "en", "s", 0, 1, 2, 3, 4, "n", "s"))
    want = brute_classes(rows, 4)
    got = minhash_dedup.near_duplicates(frame(spark, rows), shingle=4, unit_bytes=unit).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 101), (103, 101), (7, 7)]
    got = {r.node: r.root for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100, 103: 100}


def folded(length):
    """A word and its twin with letters swapped, arranged so that polynomial hashes modulo a power of two agree on them."""
    bits = [0]
    while len(bits) < length:
        bits += [1 - x for x in bits]
    return "".join("ab"[x] for x in bits[:length]), "".join("ba"[x] for x in bits[:length])


@pytest.mark.parametrize("length", [1024, 2048, 4096])
def test_arranged_words_stay_apart(spark, length):
    one, two = folded(length)
    assert quality_rules.measure(pa.array([f"{one}\n{two}\n{one}\n"]))[3].tolist() == [1]
    assert quality_rules.measure(pa.array([" ".join([one, "x", "y", two, "x", "y"])]))[4].tolist() == [0]
    fill = [f"w{i}" for i in range(60)]
    rows = [(i, " ".join([*fill[:30], w, *fill[30:]]), "en", "s", 0, 1, 2, 3, 4, "n", "s") for i, w in enumerate((one, two))]
    got = substring_dedup.remove_repeated(frame(spark, rows), window=35, layout="spaces").collect()
    assert [r.n_removed for r in got] == [0, 0]
    got = minhash_dedup.near_duplicates(frame(spark, [(i, w, "en", "s", 0, 1, 2, 3, 4, "n", "s") for i, w in enumerate((one, two))]), shingle=4).collect()
    assert all(r.kept for r in got)


def test_interning_is_exact_when_hashes_collide(monkeypatch):
    texts = ["aa bb aa cc", "bb dddddddddd", "dddddddddd aa"]
    monkeypatch.setattr(wordscan, "_block_hashes", lambda value, place, first, lens: (lens % 2).astype(wordscan.U64))
    for p in wordscan.pieces(pa.array(texts)):
        ids = wordscan.intern(p.buf, wordscan.words(p)).tolist()
    flat = " ".join(texts).split()
    assert len(set(zip(flat, ids, strict=True))) == len(set(flat)) == len(set(ids))


def test_clashing_columns_give_way(spark):
    df = frame(spark).withColumnsRenamed({"rank": "n_words", "bucket": "n_removed"})
    got = substring_dedup.remove_repeated(df, window=35, layout="spaces").collect()
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.text or "") for r in got) == brute_windows(awkward(), 35)
    assert {r.chunk for r in got} == {2}
