"""Substring, near and line dedup against brute force, with odd inputs."""

import hashlib
import random
import re

import pytest

from tsproof.llm.components import components
from tsproof.llm.line_dedup import line_dedup, patience
from tsproof.llm.near_dedup import blocks_of, near_duplicates
from tsproof.llm.substring_dedup import COVERS, substring_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, bucket string, pos int, component_id int, _gone int"


def corpus(seed: int) -> list[tuple]:
    rng = random.Random(seed)
    passage = [f"p{i}é" for i in range(55)]
    rows = []
    for i in range(60):
        words = [rng.choice("abcdefgh") * rng.randint(1, 3) for _ in range(rng.randint(0, 120))]
        if i % 3 == 0:
            at = rng.randint(0, len(words))
            words[at:at] = passage
        sep = rng.choice([" ", "\n", "  ", "\t"])
        rows.append((i, sep.join(words)))
    rows += [(100, rows[0][1]), (101, rows[0][1]), (102, rows[0][1] + " x"), (103, None), (104, ""), (105, " \n\t"), (106, "one"), (107, "One"), (None, rows[0][1]), (108, "w " * 5000)]
    rows.append(rows[5])
    return [(*r, "x", 1, 2, 3) for r in rows]


def unique(rows):
    return sorted({r[0]: r[1] or "" for r in rows if r[0] is not None}.items())


@pytest.mark.parametrize("modulus", sorted(m for m in COVERS if m <= 20))
def test_cover_meets_every_shift(modulus):
    d = COVERS[modulus]
    assert {(a - b) % modulus for a in d for b in d} == set(range(modulus))


@pytest.mark.parametrize("modulus", [1, 7, 13])
def test_substring_dedup_is_brute_force(spark, modulus):
    rows = corpus(1)
    seen, expected = set(), {}
    for i, text in unique(rows):
        words, gone = WORD.findall(text), set()
        for s in range(len(words) - 19):
            key = tuple(words[s : s + 20])
            if key in seen:
                gone.update(range(s, s + 20))
            seen.add(key)
        kept = " ".join(w for k, w in enumerate(words) if k not in gone)
        expected[i] = (i, len(words), len(gone), hashlib.sha256(kept.encode()).hexdigest(), kept)
    out = substring_dedup(spark.createDataFrame(rows, SCHEMA).repartition(5), modulus=modulus, with_text=True).collect()
    assert {r[0]: tuple(r) for r in out} == expected and len(out) == len(expected)


def test_empty_tables(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert substring_dedup(empty).count() == near_duplicates(empty).count() == line_dedup(empty).count() == 0


def shingles(text, k):
    words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text))
    return {tuple(words[i : i + k]) for i in range(len(words) - k + 1)} if len(words) >= k else ({tuple(words)} if words else set())


def near_rows():
    rng, rows = random.Random(3), []
    base = [f"w{i}" for i in range(90)]
    for i in range(150):  # a chain of edits: many members link through others only
        words = base[:]
        for _ in range(rng.randint(0, 9)):
            words[rng.randrange(90)] = f"e{rng.randrange(10**6)}"
        rows.append((1000 - i, " ".join(words)))
    return rows + [(r[0], r[1]) for r in corpus(2)]


@pytest.mark.parametrize("k,options", [(2, {}), (5, {}), (2, {"members": 7}), (5, {"members": 16, "shingles": 400})])
def test_near_duplicates_is_brute_force(spark, k, options):
    """Links of a chain cross the blocks of a bucket, however it is cut; ids lie near the ends of 64 bits too."""
    rows = near_rows() + [(2**63 - 1 - i, r[1]) for i, r in enumerate(near_rows()[:40])] + [(-(2**63) + i, "far " + r[1]) for i, r in enumerate(near_rows()[40:60])]
    sets = {i: shingles(t, k) for i, t in unique(rows)}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for n, i in enumerate(ids):
        for j in ids[:n]:
            both = len(sets[i] & sets[j])
            if both and 100 * both >= 80 * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    out = near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), shingle=k, **options).collect()
    assert sorted(map(tuple, out)) == [(i, len(sets[i]), find(i), find(i) == i) for i in ids]


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 7), (200, 201), (300, 300), (None, 4)]
    out = {r[0]: r[1] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert out == {**{i: 0 for i in range(41)}, 100: 0, 200: 200, 201: 200}


def test_blocks_pair_all_that_can_link(spark):
    """Members of different components share a group, of bounded size, whatever blocks a bucket is cut into."""
    comps = [0] * 60 + [1] * 25 + list(range(100, 130))
    rows = [(7, 0, i, 1, c) for i, c in enumerate(comps)]
    out = blocks_of(spark.createDataFrame(rows, "key long, hub long, doc_id long, n_shingles long, component_id long"), 10, 1000).collect()
    groups = {}
    for r in out:
        groups.setdefault(r["sub"], set()).add(r["doc_id"])
    met = {(a, b) for g in groups.values() for a in g for b in g}
    assert all((a, b) in met for a, x in enumerate(comps) for b, y in enumerate(comps) if x != y)
    assert max(map(len, groups.values())) <= 50 and len(out) == sum(map(len, groups.values()))


def test_patience_matches_are_common_and_increasing():
    rng = random.Random(5)
    for _ in range(200):
        a, b = ([rng.randint(0, 12) for _ in range(rng.randint(0, 25))] for _ in range(2))
        got = patience(a, b)
        assert all(a[i] == b[j] for i, j in got)
        assert all(p[0] < q[0] and p[1] < q[1] for p, q in zip(got, got[1:]))
    assert patience([1, 2, 3, 4, 9, 5], [7, 2, 3, 4, 5]) == [(1, 1), (2, 2), (3, 3), (5, 4)]


def test_line_dedup(spark):
    shared = "This line is shared by several documents of the corpus.\nAnd so is the line that comes right after it."
    rows = [
        (1, f"first own line\n{shared}\nend of one", "en"),
        (2, f"second own line\n  {shared}  \n\nend of two", "en"),
        (3, "This line is shared by several documents of the corpus.\nbut nothing after it", None),
        (4, shared, "x"),
        (5, None, "x"),
        (6, "", "x"),
        (None, shared, "x"),
        (2, f"second own line\n  {shared}  \n\nend of two", "repeated"),
    ]
    out = line_dedup(spark.createDataFrame(rows, "doc_id long, text string, _gone_text string")).collect()
    got = sorted(((r["doc_id"] or 0, r["text"], r["_lines_removed"]) for r in out), key=str)
    assert got == sorted([(1, rows[0][1], 0), (2, "second own line\n\nend of two", 2), (2, "second own line\n\nend of two", 2), (3, rows[2][1], 0), (4, "", 2), (5, None, 0), (6, "", 0), (0, shared, 0)], key=str)


LONG = "One long line that several documents of the corpus share, each of them with other neighbours around it."


def test_line_dedup_takes_one_long_line(spark):
    rows = [(1, f"before\n{LONG}\nafter"), (2, f"other before\n  {LONG.replace(' ', '  ', 3)}\nother after"), (3, LONG), (4, f"{LONG[:50]}\nmore")]
    got = {r["doc_id"]: r["text"] for r in line_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: rows[0][1], 2: "other before\nother after", 3: "", 4: rows[3][1]}


@pytest.mark.parametrize("rare", [0, 2, 8])
def test_line_dedup_is_brute_force(spark, rare):
    """Every pair of documents, every run of lines: rare seeds aligned, frequent ones by hash, the same result."""
    rng = random.Random(11)
    pool = [f"line {i} of " + "word " * rng.randint(0, 12) + "end" for i in range(12)]
    p, q, o, m, z = LONG[:40], LONG[40:80].strip(), "own one", "own two", "own three"
    rows = [(1, "\n".join([o, p, q, m, p, q, z])), (2, "\n".join(["x", p, q, "y"])), (3, "\n".join([q, p, "u", LONG, "v"])), (4, "\n".join([LONG, "w", q, p]))]
    rows += [(10 + i, "\n".join(rng.choice(pool) for _ in range(rng.randint(1, 9)))) for i in range(60)]
    # three earlier documents hold halves of a block that two later ones share whole
    block = [f"part {i} of a block that is shared" for i in range(4)]
    rows += [(200 + i, "\n".join([f"own {i}", *block[i : i + 2], f"end {i}"])) for i in range(3)] + [(300 + i, "\n".join([f"top {i}", *block, f"foot {i}"])) for i in range(2)]
    rows += [(400, "tail\n" * 3000 + LONG), (401, "other\n" * 2 + "tail\n" * 2500)]
    lines, want = {i: t.split("\n") for i, t in rows if i < 400}, {}
    for i, mine in lines.items():
        gone = set()
        for d in (x for n, x in lines.items() if n < i):
            held = {tuple(d[a:b]) for a in range(len(d)) for b in range(a + 1, len(d) + 1)}
            for a in range(len(mine)):
                for b in range(a + 1, len(mine) + 1):
                    if sum(map(len, mine[a:b])) >= 60 and tuple(mine[a:b]) in held:
                        gone |= set(range(a, b))
        want[i] = "\n".join(x for n, x in enumerate(mine) if n not in gone)
    assert want[2] == "x\ny" and want[4] == "w" and want[301] == "top 1\nfoot 1"
    got = {r["doc_id"]: r["text"] for r in line_dedup(spark.createDataFrame(rows, "doc_id long, text string"), rare=rare).collect()}
    assert got.pop(400) == "tail\n" * 2999 + "tail" and got.pop(401) == "other\nother\n"
    assert got == want
