"""Search, archives, classifiers, tiling, packing and chat against brute force or round trips."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tsproof.llm import chat, decontamination, language_id, packing, topk_search, toxicity, warc


@pytest.mark.parametrize("sizes", [{}, {"row_bytes": 9000, "query_bytes": 500}])
def test_top_k_is_brute_force(spark, sizes):
    rng = np.random.default_rng(0)
    x = np.concatenate((rng.normal(size=(300, 24)), np.round(rng.normal(size=(60, 24))), np.zeros((3, 24)))).astype(np.float32)
    rows = [(i, v.tolist(), "x") for i, v in enumerate(x)] + [(900, None, "x"), (901, [1.0] * 23 + [None], "x"), (902, [float("nan")] * 24, "x"), (903, [float("inf")] * 24, "x"), (None, [0.5] * 24, "x"), (904, [], "x"), (950, [1.0, 2.0], "x")]
    df = spark.createDataFrame([*rows, rows[0]], "vec_id long, embedding array<float>, score string")
    ints = np.floor(256 * x.astype(float)).astype(np.int64)
    expected = []
    for q in range(0, len(x), 50):
        best = sorted((-int(ints[q] @ ints[c]), c) for c in range(len(x)) if c != q)[:5]
        expected += [(q, r + 1, c, -s) for r, (s, c) in enumerate(best)]
    got = topk_search.top_k(df, df.where("vec_id % 50 = 0"), 5, **sizes).collect()
    assert sorted(map(tuple, got)) == expected
    assert topk_search.top_k(df, df.where("vec_id < 0"), 5).count() == topk_search.top_k(df.where("vec_id < 0"), df, 5).count() == 0


def vectors_of(x):
    s, e = topk_search.scaled(x)
    stats = np.concatenate([topk_search.statistics(s, n) for n in topk_search.levels_for(x.shape[1])], axis=1).astype(np.float32)
    return topk_search.Vectors(np.arange(len(x)), x, e, np.sqrt((s * s).sum(axis=1)), stats)


def test_bound_holds():
    rng = np.random.default_rng(1)
    x, q = topk_search.integers(rng.normal(size=(50, 19))), topk_search.integers(rng.normal(size=(50, 19)))
    exact = x @ q.T
    coarse, fine = (topk_search.statistics(x, s) @ topk_search.statistics(q, s).T for s in (2, 9))
    assert (coarse >= exact - 1e-6).all() and (fine >= exact - 1e-6).all() and fine.mean() < coarse.mean()


def test_every_level_drops_pairs_of_clustered_vectors():
    """Smooth vectors around few centres: each level leaves fewer pairs, and the result is brute force."""
    rng = np.random.default_rng(2)
    shapes = np.cumsum(rng.normal(size=(40, 64)), axis=1) + 8 * rng.normal(size=(40, 1))
    x = shapes[rng.integers(0, 40, 3000)] + 0.3 * np.cumsum(rng.normal(size=(3000, 64)), axis=1) + 0.1 * rng.normal(size=(3000, 64))
    rows, shares = vectors_of(x), []
    q = rows.take(np.arange(0, 3000, 50))
    best = topk_search.search(q, rows, 5, shares)
    left = [sum(s[i] if i < len(s) else 0 for s in shares) for i in range(len(topk_search.levels_for(64)) + 2)]
    assert left[0] > 4 * left[1] and all(a > b for a, b in zip(left, left[1:]))
    score = topk_search.integers(q.x) @ topk_search.integers(x).T
    score[np.arange(len(q.ids)), q.ids] = -np.inf
    order = np.lexsort((np.broadcast_to(np.arange(3000), score.shape), -score), axis=1)[:, :5]
    assert (best.ids == order).all() and (best.score == np.take_along_axis(score, order, 1)).all()


def test_components_of_any_size_are_exact(spark):
    rows = [(0, [1e12, 1.0]), (1, [3.0, 1.0]), (2, [3.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = topk_search.top_k(df, df.where("vec_id = 0"), 2).collect()
    big = 256 * 10**12
    assert [tuple(r)[2:] for r in sorted(got)] == [(2, big * 768 + 256 * 512), (1, big * 768 + 256 * 256)]
    rng = random.Random(6)
    rows = [(i, [rng.choice([0.0, 1.0, -1.5, 1e200, -1e200, 1e307]) if i else 0.0, 2.0 * rng.randint(-3, 3), 1.0]) for i in range(60)]
    rows += [(100, [0.0, 0.0, 1e13])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    whole = lambda v: [int(c * 256) if abs(c) < 1e12 else int(c) * 256 for c in v]
    want = []
    for i in (0, 100):
        of = {j: sum(a * b for a, b in zip(whole(dict(rows)[i]), whole(v))) for j, v in rows if j != i}
        want += [(i, r + 1, j, of[j]) for r, j in enumerate(sorted(of, key=lambda j: (-of[j], j))[:5])]
    got = topk_search.top_k(df, df.where("vec_id in (0, 100)"), 5).collect()
    assert sorted(map(tuple, got)) == want
    for vector in ([1.0, 0.0, 0.0], [-1.0, 0.0, 0.0]):  # above and below 64 bits, with fewer rows than k
        few = spark.createDataFrame([(1, vector), (2, [1e300, 0.0, 1.0])], "vec_id long, embedding array<double>")
        with pytest.raises(Exception, match="64 bits"):
            topk_search.top_k(few, few.where("vec_id = 1"), 5).collect()


def test_warc_round_trip(spark):
    rows = [(1, "http://a/ b", "<p>é</p>"), (2, None, "<p>é</p>"), (3, "http://c", ""), (4, "http://d", None), (5, "http://e\r\nX: y", "tail\r\n\r\n"), (None, "http://f", "<p>é</p>"), (6, "http://g", "z" * 300_000), (6, "http://g", "z" * 300_000)]
    pages = spark.createDataFrame([(*r, "k") for r in rows], "page_id long, url string, html string, digest string")
    folder, index = warc.write_archives(pages, archive_bytes=1000)
    assert index.count() == len(rows) and index.select("archive").distinct().count() > 1
    out = warc.read_archives(folder, index, with_payload=True).collect()
    got = sorted(((r["page_id"] or 0, r["record_type"], r["refers_to"], r["payload_bytes"], r["html"] if r["record_type"] == "response" else None) for r in out), key=str)
    heads = {"<p>é</p>": 2, "": 4, "tail\r\n\r\n": 5, "z" * 300_000: 6}
    expected = []
    for i, _, html in rows:
        html = html or ""
        lead = i == heads[html]
        expected.append((i or 0, "response" if lead else "revisit", None if lead else heads[html], len(html.encode()), html if lead else None))
    assert got == sorted(expected, key=str)
    some = warc.read_archives(folder, index.where("page_id = 5")).collect()
    assert [r["url"] for r in some] == ["http://e%0D%0AX:%20y"]
    assert warc.round_trip(pages.where("page_id < 0")).count() == 0


def test_merged_ranges_cover_all():
    rng = random.Random(0)
    ranges, at = [], 0
    for _ in range(100):
        at += rng.randint(0, 50)
        ranges.append((at, 10))
        at += 10
    merged = warc.merge_ranges(ranges, gap=20, most=200)
    assert [i for m in merged for i in m[2]] == list(range(100)) and len(merged) < 100
    assert all(o <= ranges[i][0] and ranges[i][0] + 10 <= o + n for o, n, members in merged for i in members)


WORDS = [f"word{i}" for i in range(400)]


def sentence(rng, *extra):
    words = [rng.choice(WORDS) for _ in range(25)]
    for e in extra:
        words.insert(rng.randrange(25), e)
    return " ".join(words)


def test_counterfactual_penalty_frees_neutral_mentions():
    rng = random.Random(1)
    texts, labels = [], []
    for i in range(600):
        toxic = i % 3 == 0
        named = rng.random() < (0.8 if toxic else 0.05)
        texts.append(sentence(rng, *(["vilefool"] if toxic and i % 2 else []), *(["muslim"] if named else [])))
        labels.append(toxic)
    labels = np.array(labels)
    plain, fair = (toxicity.fit(texts, labels, labels.mean(), **p) for p in ({"penalty": 0.0}, {}))  # {}: as shipped
    neutral = [sentence(rng, "muslim") for _ in range(100)]
    swapped = [toxicity.counterfactuals(t) for t in neutral]
    assert all("christian" in t for t in swapped)
    gap = [np.abs(m.scores(pa.array(neutral)) - m.scores(pa.array(swapped))).mean() for m in (plain, fair)]
    false = [(m.scores(pa.array(neutral)) >= 0.5).mean() for m in (plain, fair)]
    assert gap[1] < gap[0] / 5 and false[1] < false[0]
    assert (fair.scores(pa.array([sentence(rng, "vilefool") for _ in range(50)])) > 0.5).mean() > 0.9


def test_every_language_has_terms_to_swap():
    for text, swapped in (("die Frauen und Männer", "die Männer und Frauen"), ("les femmes musulmanes", "les hommes chrétiennes"), ("la mujer judía", "la hombre católica"), ("muslim men", "christian women")):
        assert toxicity.counterfactuals(text).lower() == swapped.lower()
    terms = [x for pair in toxicity.IDENTITIES for x in pair]
    assert len(terms) == len(set(terms)) and all(x == x.lower() for x in terms)


def test_toxicity_held_out(spark):
    rng = random.Random(2)
    rows = [(i, sentence(rng, *(["vilefool"] if i % 4 == 0 else []))) for i in range(400)] + [(1000, None), (1001, ""), (1002, "vilefool " + "word1 " * 30_000), (None, "x")]
    docs = spark.createDataFrame([(*r, "k") for r in rows], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(400)] + [(0, None), (None, 1)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels, F.col("doc_id") % 2 == 1)
    out = {r["doc_id"]: r["_score"] for r in toxicity.score(docs, model).collect()}
    assert len(out) == len(rows) and all(0 <= s <= 1 for s in out.values())
    right = sum((out[i] >= 0.3) == (i % 4 == 0) for i in range(400))
    assert right >= 396
    none = toxicity.train(docs, labels.where("toxic = 5"))
    assert {round(r["_score"], 6) for r in toxicity.score(docs, none).collect()} == {0.0}


def test_language_id(spark):
    rng = random.Random(3)
    vocab = {"aa": ["straße", "über", "nicht", "und", "der"], "bb": ["où", "élève", "être", "pas", "le"], "cc": ["the", "and", "with", "that", "of"]}
    rows = [(i, " ".join(rng.choice(vocab[lang]) for _ in range(30)), lang) for i, lang in enumerate(sorted(vocab) * 60)]
    odd = [(1000, None, "aa"), (1001, "", "bb"), (1002, "12 34 %%", "cc"), (1003, "über " * 20_000, None), (1004, "日本語", None)]
    docs = spark.createDataFrame(rows + odd, "doc_id long, text string, lang string")
    model = language_id.train(docs, F.col("doc_id") % 2 == 1)
    assert model.langs == ["aa", "bb", "cc"]
    out = {r["doc_id"]: r for r in language_id.predict(docs, model).collect()}
    assert all(out[i]["lang_pred"] == lang for i, _, lang in rows)
    assert [out[i]["lang_pred"] for i in (1000, 1001, 1002, 1003)] == ["und", "und", "und", "aa"]
    assert out[1004]["lang_pred"] in vocab and all(0 <= r["score"] <= 1 for r in out.values())
    assert language_id.predict(docs.where("doc_id < 0"), model).count() == 0
    empty = language_id.train(docs.where("doc_id < 0"))
    assert {r["lang_pred"] for r in language_id.predict(docs, empty).collect()} == {"und"}


def test_code_length_is_the_model():
    """The table of frozen code lengths against a direct walk of the context tree."""
    texts = [b"abracadabra", b"banana band"]
    model = language_id.fit({"x": texts})
    counts: dict = {}
    for t in texts:
        s = b"   " + t
        for i in range(3, len(s)):
            for k in range(4):
                ctx = counts.setdefault(s[i - k : i], {})
                ctx[s[i]] = ctx.get(s[i], 0) + 1

    def bits(ctx, c):
        if ctx not in counts:
            return bits(ctx[1:], c) if ctx else 8.0
        seen = counts[ctx]
        n, u = sum(seen.values()), len(seen)
        if c in seen:
            return -np.log2(seen[c] / (n + u))
        return -np.log2(u / (n + u)) + (bits(ctx[1:], c) if ctx else 8.0)

    text = b"   banabrad acab"
    expected = sum(bits(text[i - 3 : i], text[i]) for i in range(3, len(text)))
    got = model.code_lengths(pa.array(["banabrad acab", "", "ban"]))
    assert abs(got[0, 0] - expected) < 1e-3 and got[1, 0] == 0


def brute_tiles(a, b, size):
    used_a, used_b, out = set(), set(), []
    while True:
        best = None
        for i in range(len(a)):
            for j in range(len(b)):
                n = 0
                while i + n < len(a) and j + n < len(b) and a[i + n] == b[j + n] and i + n not in used_a and j + n not in used_b:
                    n += 1
                if n >= size and (best is None or (-n, i, j) < (-best[2], best[0], best[1])):
                    best = (i, j, n)
        if best is None:
            return out
        out.append(best)
        used_a.update(range(best[0], best[0] + best[2]))
        used_b.update(range(best[1], best[1] + best[2]))


def test_tiles_are_greedy():
    rng = random.Random(4)
    for _ in range(60):
        a, b = ([rng.randint(0, 3) for _ in range(rng.randint(3, 40))] for _ in range(2))
        want, words = brute_tiles(a, b, 3), [np.array(x, np.uint64) for x in (a, b)]
        for most in (1 << 20, 0):  # with all seeds listed, and with none
            assert decontamination.tiles(*words, 3, most=most) == want
        # hashes that are equal for different words: a tile never crosses one
        bad = decontamination.tiles(*words, 3, lambda d, i, n: np.array([a[d + k] == b[i + k] != 0 for k in range(n)], bool))
        assert bad == decontamination.tiles(np.where(words[0] == 0, np.uint64(99), words[0]), words[1], 3)


def test_tiles_of_periodic_words_stay_small():
    """One word repeated on both sides has n * m equal seeds; they are never listed."""
    import tracemalloc

    a, b = np.zeros(200_000, np.uint64), np.zeros(4000, np.uint64)
    tracemalloc.start()
    assert decontamination.tiles(a, b, 5) == [(0, 0, 4000)]
    assert tracemalloc.get_traced_memory()[1] < 100 << 20
    tracemalloc.stop()


@pytest.mark.parametrize("block_bytes", [1 << 20, 10])
def test_reordered_passages_are_caught(spark, block_bytes):
    item = [f"k{i}" for i in range(40)]
    moved = " ".join(item[20:]) + " filler words here " + " ".join(item[:20])
    docs = [(1, "x " * 50 + moved.upper()), (2, "y " + " ".join(item[:12])), (3, None), (4, ""), (5, "Tiny, passage of five words!"), (6, "clean " * 9000), (None, moved), (1, moved)]
    docs += [(12, "before this: Very, short item here; and after"), (13, "short item"), (14, "a short item in a text"), (15, "y")]
    bench = [(7, " ".join(item)), (8, "tiny passage of five words"), (9, None), (None, "clean"), (10, ""), (11, "y"), (16, "very short item here"), (17, "short item")]
    d = spark.createDataFrame([(*r, 0) for r in docs], "doc_id long, text string, item_id int")
    b = spark.createDataFrame(bench, "item_id long, text string")
    out = sorted(((r["doc_id"] or 0, r["_leak_item"], round(r["_leak_coverage"] or 0, 3), r["_leak_tiles"]) for r in decontamination.find_leaks(d, b, block_bytes=block_bytes).collect()), key=str)
    assert out == sorted([(1, 7, 1.0, 2), (2, 7, 0.3, 1), (3, None, 0, None), (4, None, 0, None), (5, 8, 1.0, 1), (6, None, 0, None), (0, 7, 1.0, 2), (1, 7, 1.0, 2), (12, 16, 1.0, 1), (13, 17, 1.0, 1), (14, None, 0, None), (15, 11, 1.0, 1)], key=str)
    assert sorted(r["doc_id"] for r in decontamination.decontaminate(d, b).collect()) == [2, 3, 4, 6, 14]
    assert decontamination.decontaminate(d, b.where("item_id < 0")).count() == len(docs)


def test_packing(spark):
    rng = random.Random(5)
    rows = [(i, rng.choice([0, 1, 7, 100, 511, 512, 900, 5000, 20_000])) for i in range(500)] + [(None, 10), (None, 10), (3, 4), (600, None)]
    out = packing.best_fit(spark.createDataFrame(rows, "doc_id long, n_tokens long"), shard_rows=100).toPandas()
    assert out.n_tokens.sum() == sum(n or 0 for _, n in rows)
    some = out[out.n_tokens > 0]
    bins = some.sort_values("bin_offset").groupby("bin_id")
    for _, b in bins:
        ends = (b.bin_offset + b.n_tokens).tolist()
        assert b.bin_offset.tolist() == [0, *ends[:-1]] and ends[-1] <= b.capacity.iloc[0]
        assert b.capacity.iloc[0] == min(c for c in packing.CAPACITIES if c >= ends[-1])
    assert out[out.n_tokens == 0].bin_id.isna().all()
    assert packing.best_fit(spark.createDataFrame([], "doc_id long, n_tokens long")).count() == 0


def total(caps, price):
    return sum(price(c) for c in caps.tolist())


def optimum(lengths, capacities, price):
    """Least cost over all ways to group the pieces, by dynamic programming over subsets."""
    n = len(lengths)
    load = [sum(lengths[i] for i in range(n) if m >> i & 1) for m in range(1 << n)]
    one = [min((price(c) for c in capacities if c >= x), default=float("inf")) for x in load]
    best = [0.0] + [float("inf")] * ((1 << n) - 1)
    for m in range(1, 1 << n):
        low, s = m & -m, m
        while s:
            if s & low:
                best[m] = min(best[m], best[m ^ s] + one[s])
            s = (s - 1) & m
    return best[-1]


def test_pack_against_the_optimum():
    rng, exact, ratio = random.Random(8), 0, []
    for price in (packing.cost, lambda c: c, lambda c: 3 + c, lambda c: c**0.5):
        for _ in range(60):
            lengths = [rng.randint(1, 16) for _ in range(rng.randint(1, 8))]
            bins, _, caps = packing.pack(np.array(lengths), (4, 8, 16), price)
            load = np.bincount(bins, lengths)
            assert (load <= caps).all() and all(c == min(x for x in (4, 8, 16) if x >= u) for u, c in zip(load, caps))
            got, least = total(caps, price), optimum(lengths, (4, 8, 16), price)
            assert got >= least - 1e-9
            exact += got <= least + 1e-9
            ratio.append(got / least)
    assert exact >= 0.85 * len(ratio) and np.mean(ratio) < 1.02


def test_pack_opens_small_sizes_where_they_are_cheaper():
    lengths = np.array([3] * 40 + [9])
    flat = packing.pack(lengths, (4, 8, 16), lambda c: {4: 1.0, 8: 5.0, 16: 9.0}[c])
    steep = packing.pack(lengths, (4, 8, 16), lambda c: {4: 5.0, 8: 6.0, 16: 7.0}[c])
    assert sorted(flat[2].tolist()) == [4] * 38 + [16] and sorted(steep[2].tolist())[0] >= 4 and (steep[2] == 16).sum() == 9


def test_pack_never_costs_more_than_one_plan():
    """Choosing jointly is at least as good as the size of least cost a token, whatever the load."""
    rng = random.Random(9)
    for _ in range(6):
        lengths = np.array([min(4096, int(rng.lognormvariate(rng.choice([4, 5, 6]), 1)) + 1) for _ in range(1500)])
        single = packing.place(lengths, packing.CAPACITIES, packing.least_per_token(packing.CAPACITIES, packing.cost))
        assert total(packing.pack(lengths)[2], packing.cost) <= total(single[2], packing.cost)


CHAT = "conv_id long, turn long, role string, text string, head string"


def test_chat_rotation(spark):
    rows = [(1, 0, "system", "rules"), (1, 1, "ann", "hi <|im_end|>"), (1, 2, "bob b", None), (1, 3, None, "x"), (2, 0, "system", "alone"), (None, 0, "ann", "y"), (1, 1, "ann", "hi <|im_end|>")]
    out = chat.rotate(spark.createDataFrame([(*r, "z") for r in rows], CHAT)).collect()
    assert len(out) == 3 * 5 and {r["perspective"] for r in out} == {"ann", "bob b", None}
    own = [r for r in out if r["perspective"] == "ann" and r["turn"] == 1]
    assert len(own) == 2 and own[0]["rendered"] == "<|im_start|>assistant\nhi <| im_end|><|im_end|>\n"
    assert own[0]["rendered"][own[0]["mask_start"] : own[0]["mask_end"]] == "hi <| im_end|><|im_end|>"
    other = next(r for r in out if r["perspective"] == "ann" and r["turn"] == 2)
    assert other["rendered"] == "<|im_start|>user name=bob%20b\n<|im_end|>\n" and other["mask_start"] is None
    assert chat.rotate(spark.createDataFrame([], CHAT)).count() == chat.dialogues(spark.createDataFrame([], CHAT)).count() == 0


def test_chat_names_are_injective(spark):
    names = ["A B", "A_B", "A%20B", "A+B", "a b", "é", "%C3%A9", "*", "~", "", "unnamed", None, "System"]
    rows = [(1, i, n, f"says {i}", "") for i, n in enumerate(names)]
    out = chat.rotate(spark.createDataFrame(rows, CHAT)).where("perspective = 'A B'").collect()
    heads = {r["rendered"].split("\n")[0] for r in out}
    assert len(out) == len(heads) == len(names)


def test_chat_dialogues(spark):
    """Assembled parts are the pieces in order, and the masks are exactly the speaker's own words, in very long turns too."""
    rows = [(1, i, ("ann", "bob", None)[i % 3], f"turn {i} " + "word " * (30_000 if i == 4 else i), "") for i in range(20)] + [(1, None, "ann", "early", "")]
    turns = spark.createDataFrame(rows, CHAT)
    out = chat.dialogues(turns, span=8).orderBy("perspective", "part").collect()
    assert [(r["perspective"], r["part"]) for r in out] == [(x, k) for x in (None, "ann", "bob") for k in (-1, 0, 1, 2)]
    pieces = chat.rotate(turns).collect()
    for who in ("ann", "bob", None):
        mine = sorted((r for r in pieces if r["perspective"] == who), key=lambda r: -1 if r["turn"] is None else r["turn"])
        parts = [r for r in out if r["perspective"] == who]
        assert "".join(r["text"] for r in parts) == "".join(r["rendered"] for r in mine)
        assert [r["text"][a:b] for r in parts for a, b in r["masks"]] == [r["rendered"][r["mask_start"] : r["mask_end"]] for r in mine if r["speaker"] == who]
