"""Small texts against brute force, and the defined edge cases, for the operators that SQL does not check."""

import hashlib
import random
import zlib
from collections import Counter
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from simsearch.llm import common, decontaminate, encoding, jaccard, pitman_yor, quality, repair, rules, separators, suffixes, toxicity
from simsearch.llm.components import components

DOCS = "doc_id long, text string"
EDGE = [(1, None), (2, ""), (3, "  \n"), (4, "one"), (4, "one"), (None, "a b c d e f g h i j k l"), (5, "ü" * 900), (6, "a  b\n c\x0bd <|endoftext|> 1.5%%")]


def brute_removed(texts, length):
    starts = Counter(t[p : p + length] for t in texts for p in range(len(t) - length + 1))
    out = []
    for t in texts:
        cover = bytearray(len(t))
        for p in range(len(t) - length + 1):
            if starts[t[p : p + length]] > 1:
                cover[p : p + length] = b"\1" * length
        out.append((sum(cover), hashlib.sha256(bytes(b for b, c in zip(t, cover) if not c)).hexdigest()))
    return out


@pytest.mark.parametrize("most", [512, 2])
def test_repeats_match_brute_force(spark, most):
    rng = random.Random(3)
    word = lambda n: "".join(rng.choice("abcdefgh é") for _ in range(n))
    passage = word(700)
    texts = [word(200) + passage[: rng.randint(230, 700)] + word(150) for _ in range(12)] + [passage] * 2 + ["ab" * 500, word(399), "", None]
    docs = spark.createDataFrame(list(enumerate(texts)), DOCS).withColumn("uid", F.lit("clash"))
    got = {r.doc_id: r for r in suffixes.remove_repeats(docs, length=400, most=most).collect()}
    every = [(t or "").encode() for t in texts]
    for i, ((n, sha), (n_short, _)) in enumerate(zip(brute_removed(every, 400), brute_removed(every, 256))):
        assert (sum(s.end - s.begin for s in got[i].spans), got[i].kept_sha256, got[i].n_short) == (n, sha, n_short)
    assert suffixes.remove_repeats(docs.limit(0)).count() == 0


def test_maximal_repeats_match_brute_force(spark):
    """Every occurrence of every string of the length that occurs twice lies in a group of its own string's occurrences."""
    rng = random.Random(5)
    word = lambda n: "".join(rng.choice("abc") for _ in range(n))
    passage = word(260)
    texts = [word(60) + passage[a:b] + word(60) for a, b in ((0, 260), (20, 240), (0, 130), (100, 260))] + [word(200)]
    size = 100
    found = suffixes.maximal_repeats(spark.createDataFrame(list(enumerate(texts)), DOCS), length=size).collect()
    groups = {}
    for r in found:
        groups.setdefault((r.repeat, r.n_bytes), []).append((r.doc_id, r.begin))
    for (_, n), places in groups.items():
        assert len({texts[i][b : b + n] for i, b in places}) == 1 and len(places) > 1  # one string
        assert len({texts[i][b - 1 : b] for i, b in places}) > 1 or len({texts[i][b + n : b + n + 1] for i, b in places}) > 1 or n >= size
    at = {}
    for i, t in enumerate(texts):
        for p in range(len(t) - size + 1):
            at.setdefault(t[p : p + size], []).append((i, p))
    for places in at.values():
        if len(places) > 1:
            (i, p), others = places[0], set(places[1:])
            seen = set()
            for (_, n), members in groups.items():
                for j, b in members:
                    if j == i and b <= p and p + size <= b + n:
                        seen |= {(x, y + p - b) for x, y in members}
            assert others <= seen


def test_repeat_groups_have_all_occurrences():
    groups = list(suffixes.repeat_groups([b"xab", b"yab", b"zzb"], [b"cdef", b"cdeg", b"cdeh"], 4))
    assert (2, 3, [0, 1]) in [(a, b, sorted(m)) for a, b, m in groups]
    assert (1, 3, [0, 1, 2]) in [(a, b, sorted(m)) for a, b, m in groups]


def test_encoder_equals_tokenizer(monkeypatch):
    enc = encoding.Encoder(repair.default_tokenizer(), cache_size=5)
    texts = ["the word, and thandanst. Ünïté! ärger; naïve? l'eau d'or don't x1 1x A.B ab.. ª µm \u0149x é́a ñ", "the word. the, the", "Hello  world", " lead", "trail ", "a\n b", "a b\x0bc d", "x" * 300 + " y", "é ü <|endoftext|> z", "1 2\t3", ""] * 2
    texts += [" ".join("ab cde. É f-g".split()[i % 4] * (1 + i % 30) for i in range(n)) for n in (1, 40, 400)] + ["lead, lead lead " + "z" * 70 + " end "]
    monkeypatch.setattr(encoding, "_GROUP", 90)
    assert enc.encode(texts) == [np.array(enc.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]


def test_encoder_keeps_parts_that_come_again(monkeypatch):
    """A full table keeps what was met again and lets the rest go (before, it forgot all and learnt the usual words anew)."""
    enc = encoding.Encoder(repair.default_tokenizer(), cache_size=60)
    monkeypatch.setattr(encoding, "_GROUP", 200)
    learnt, learn = [], enc._learn
    monkeypatch.setattr(enc, "_learn", lambda parts: learnt.extend(parts) or learn(parts))
    usual = [f"word{chr(97 + i)}" for i in range(20)]
    for g in range(40):
        texts = [" ".join(["a", *usual, *(f"n{g}.{i}" for i in range(15))])]
        assert enc.encode(texts) == [np.array(enc.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]
        assert len(enc.names) <= 60 + 36 and len(enc.proof) == len(enc.again) == len(enc.names)
    assert max(Counter(p for p in learnt if p in usual).values()) == 1


def test_merges_get_many_parts_at_a_time(monkeypatch):
    """Words go to the merges by the dozen (before, one by one), and what the pattern would cut otherwise doesn't go there."""
    enc = encoding.Encoder(repair.default_tokenizer())
    texts = ["lead thanin.\nThha, ershin,%%% rent$$$ 12.5kg (a_b) x=1 l'eau 'd a\n\nb \u00d7\u00f7 \u024f\u0250 \u00e9\u00c0\u0142! \u20ac5 a\u0301b \u00b2 \u0663 \u4e2d\u6587 #$% -- c\nd end\n", "a \nb", "x \u00c9t\u00e9\n.\nz \u0249 \u00c8"]
    texts += [" ".join(f"{a}{b}{c}{d}" for a in ("th", "On", "\u00fc", "9", "%") for b in ("er", "\n", ",", "\u00df", "ing") for c in ("a", ".", "7", "\n", "''") for d in ("", "B", "!", "0"))]
    want = [np.array(enc.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]
    assert enc.encode(texts) == want

    def one(*_):
        raise AssertionError("a single word")

    monkeypatch.setattr(enc, "merges", one)
    word = " ".join(f"w{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(600))
    assert enc.encode([". " + word]) == [np.array(enc.tokenizer.encode(". " + word, add_special_tokens=False).ids, "<u4").tobytes()]


def test_other_operators_let_the_encoder_go():
    """A worker that goes on to texts of another operator does not keep the encoder's table; one that encodes on does."""
    enc = encoding.encoder_alone(repair.default_tokenizer())
    assert encoding.encoder_alone(repair.default_tokenizer()) is enc
    jaccard.pieces(iter([]))
    assert encoding.encoder_alone(repair.default_tokenizer()) is not enc


def test_grammar_round_trip_and_span():
    rng = np.random.default_rng(1)
    x = rng.integers(0, 9, 6000).astype("<u4")
    ends = np.array([0, 1, 500, 5999])
    symbols, new_ends, rules_, lengths = repair.compress(x, ends, 100, least=4)
    inner = np.setdiff1d(np.arange(len(symbols) - 1), new_ends)
    assert max(Counter(zip(symbols[inner].tolist(), symbols[inner + 1].tolist())).values()) < 4  # no frequent pair is left
    grammar = repair.Grammar(rules_, lengths, 100)
    assert (grammar.expand(symbols) == x).all() and len(symbols) < len(x)
    assert (np.cumsum(grammar.sizes(symbols))[new_ends] - 1 == ends).all()
    assert (grammar.span(symbols, 1234, 2345) == x[1234:2345]).all()
    for tiny in ([], [7], [7, 7], [7] * 1000):
        x = np.array(tiny, "<u4")
        symbols, _, rules_, lengths = repair.compress(x, np.array([len(x) - 1] if tiny else [], np.int64), 100, least=2)
        assert (repair.Grammar(rules_, lengths, 100).expand(symbols) == x).all()


def test_token_files(spark):
    docs = spark.createDataFrame(EDGE, DOCS)
    got = repair.round_trip(docs, repair.default_tokenizer(), shard_tokens=20).collect()
    t = encoding.Encoder(repair.default_tokenizer()).tokenizer
    want = Counter((i, len(ids := t.encode(x or "", add_special_tokens=False).ids) + 1, zlib.crc32(np.array([*ids, 2], "<u4").tobytes())) for i, x in EDGE)
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in got) == want
    at = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == at
        at += r.n_tokens
    assert repair.round_trip(spark.createDataFrame([], DOCS), repair.default_tokenizer()).count() == 0


def test_separator_scan_stitches_blocks(spark):
    flat = [5, 9, 9, 7, 5, 5, 8, 8, 8, 8, 8, 5, 3]
    for size in (1, 2, 5, 50):
        rows = [(0, b, np.array(flat[a : a + size], "<u2").tobytes()) for b, a in enumerate(range(0, len(flat), size))] + [(1, 0, b"")]
        got = separators.scan(spark.createDataFrame(rows, "file int, block int, data binary"), 5).orderBy("ordinal").collect()
        assert [(r.start, r.n_tokens, r.complete) for r in got] == [(0, 0, True), (1, 3, True), (5, 0, True), (6, 5, True), (12, 1, False)]


def test_leaks_edges(spark):
    bench = spark.createDataFrame([(1, "a b c"), (2, None), (3, " ".join(f"w{i}" for i in range(12))), (None, "one"), (4, "a b c")], "item_id long, text string")
    docs = spark.createDataFrame([*EDGE, (7, "x A, B; c y"), (8, "w0 " * 5 + " ".join(f"W{i}" for i in range(1, 12)))], DOCS)
    for block in (2_000_000, 2):
        got = {(r.doc_id, r.n_words, len(r.hit), ",".join(r["items"])) for r in decontaminate.find_leaks(docs, bench, block_words=block).collect()}
        assert {(7, 5, 3, "1,4"), (1, 0, 0, ""), (4, 1, 0, ""), (8, 16, 12, "3"), (None, 12, 3, "1,4")} <= got


def brute_shingles(text, n):
    words = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").split()
    return {tuple(words[i : i + min(n, len(words))]) for i in range(max(1, len(words) - n + 1))} if words else set()


def test_sets_match_brute_force():
    rng = random.Random(8)
    texts = ["", "  ", "one", "one TWO", "One two", "a b c d", "a b c d a b c d a b c"] + [" ".join(rng.choice("abcÄ") * rng.randint(1, 2) for _ in range(rng.randint(0, 60))) for _ in range(50)]
    for n in (1, 3, 5):
        want = [brute_shingles(t, n) for t in texts]
        sets = jaccard.Sets([t.encode() for t in texts], n)
        assert sets.size.tolist() == [len(w) for w in want]
        names = list(zip(*(x.tolist() for x in sets.digests())))
        for i, a in enumerate(texts):
            assert (jaccard.shingles(a.encode(), n) == sets[i]).all()
            for j in range(i):
                assert len(np.intersect1d(sets[i], sets[j])) == len(want[i] & want[j])
                assert (names[i] == names[j]) == (want[i] == want[j])


@pytest.mark.parametrize(("parts", "spared"), [(3, 1), (4, 1), (5, 2), (2, 1)])
def test_signatures_lose_no_similar_pair(parts, spared):
    rng = np.random.default_rng(5)
    bands = jaccard.Bands(80, parts, spared)
    words = [f"w{i}" for i in range(5000)]
    for n in (1, 4, 5, 9, 30, 200):
        for _ in range(25):
            a = list(rng.permutation(words)[:n])
            b = a.copy()
            for _ in range(rng.integers(0, max(1, n // 5) + 1)):
                if rng.random() < 0.5 and len(b) > 1:
                    b.pop(rng.integers(len(b)))
                else:
                    b.append(f"x{rng.integers(1000)}")
            sets = jaccard.Sets([" ".join(x).encode() for x in (a, b)], 1)
            inter, union = len({*a} & {*b}), len({*a} | {*b})
            if 100 * inter >= 80 * union and inter < union:
                sig, whose = bands.signatures(sets, np.ones(2, bool))
                assert set(sig[whose == 0].tolist()) & set(sig[whose == 1].tolist())
                bits = sets.parities().view(np.uint64)
                assert np.bitwise_count(bits[0] ^ bits[1]).sum() <= union - inter


def test_members_do_not_depend_on_how_rows_are_held(spark):
    """Every two classes that share a signature are tied through the rows of that signature, whatever met where."""
    words = [" ".join(f"w{(i * 7 + j) % 40}" for j in range(12)) for i in range(40)] * 2
    docs = spark.createDataFrame([(t,) for t in words], "text string").repartition(5)
    bands = lambda: jaccard.Bands(80)
    sets = jaccard.Sets([w.encode() for w in words[:40]], 1)
    sig, whose = bands().signatures(sets, np.ones(40, bool))
    of = {}
    for s, w in zip(sig.tolist(), sets.digests()[0][whose].tolist()):
        of.setdefault(s, set()).add(w)
    want = {s: x for s, x in of.items() if len(x) > 1}
    for flush, slices in ((1_000_000, 1), (50, 1), (1, 2)):
        got = {}
        for part in range(slices):
            for r in jaccard.members(jaccard.signature_rows(docs, 1, bands(), part, slices, flush)).collect():
                got.setdefault(r.sig, []).append((r.low, r.cls))
        assert {s: {c for _, c in x} for s, x in got.items()} == want
        for x in got.values():
            tied = {min(c for _, c in x)}
            for _ in x:
                tied |= {c for low, c in x if low in tied} | {low for low, c in x if c in tied}
            assert tied == {c for _, c in x}


def test_near_duplicates_edges(spark):
    base = [f"w{i}" for i in range(60)]
    rows = [*EDGE, (20, " ".join(base)), (21, " ".join([*base, "end"])), (22, " ".join(base).upper()), (23, " ".join(base[:30]))]
    got = [(r.doc_id, r.component_id) for r in jaccard.near_duplicates(spark.createDataFrame(rows, DOCS), n=5, percent=80).collect()]
    assert sorted(x for x in got if (x[0] or 0) >= 20) == [(20, 20), (21, 20), (22, 20), (23, 23)]
    assert got.count((4, 4)) == 2 and len(got) == len(rows)
    assert jaccard.near_duplicates(spark.createDataFrame([], DOCS)).count() == 0


def test_near_duplicates_match_brute_force_and_clean_up(spark):
    rng = random.Random(2)
    base = [[rng.choice("abcdefghijklmnop") + rng.choice("xyz") for _ in range(rng.randint(1, 70))] for _ in range(12)]
    texts = []
    for words in base * 5:
        words = words.copy()
        for _ in range(rng.randint(0, 3)):
            words[rng.randrange(len(words))] = rng.choice("qrst")
        texts.append(" ".join(words))
    sets = [brute_shingles(t, 3) for t in texts]
    label = list(range(len(texts)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and 100 * len(a & b) >= 80 * len(a | b) and label[i] != label[j]:
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if x == old else x for x in label]
    before = sorted(Path(common.shared_dir(spark).removeprefix("file://")).iterdir())
    docs = spark.createDataFrame(list(enumerate(texts)), DOCS).repartition(6)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.near_duplicates(docs, n=3, percent=80).collect()}
    assert got == {i: (len(s), c) for i, (s, c) in enumerate(zip(sets, label))}
    left = {p.name.rsplit("-", 1)[0] for p in Path(common.shared_dir(spark).removeprefix("file://")).iterdir() if p not in before}
    assert left == {"profiles", "components"}  # what the lazy result reads


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(9)] + [(20, 30), (30, 20), (5, 5)], "a long, b long")
    assert {(r.node, r.component) for r in components(links).collect()} == {(i, 0) for i in range(10)} | {(20, 20), (30, 20)}


def test_seating_matches_one_by_one():
    rng, push, d = np.random.default_rng(1), 3.0, 0.5

    def slow(n):
        t, m = 1, 1
        while m < n:
            t += rng.random() < push / (push + m - d * t)
            m += 1
        return t

    fast = pitman_yor.seat(np.full(4000, 40), np.full(4000, push), d, rng)
    assert abs(fast.mean() - np.mean([slow(40) for _ in range(4000)])) < 0.25
    assert (pitman_yor.seat(np.array([0, 1]), np.ones(2), d, rng) == [0, 1]).all()
    waiting = pitman_yor.seat(np.full(4000, 40), np.full(4000, push), d, rng, coins=1)
    assert abs(waiting.mean() - fast.mean()) < 0.15
    n, keys = np.array([2, 900, 3, 2500, 41]), np.arange(5, dtype=np.uint64)
    tables = [pitman_yor.seat_by_coins(n, n * 0.1, d, pitman_yor.Draws(keys, 1, 1), np.arange(5), block).tolist() for block in (100, 1000, 1 << 20)]
    assert tables[0] == tables[1] == tables[2]  # stretches do not change what is drawn
    import math

    x = np.array([0.5, 1.0, 3.7, 50.0, 1e6])
    assert np.allclose(pitman_yor.log_gamma(x), [math.lgamma(v) for v in x], rtol=1e-9)


def test_chain_marginals_match_enumeration():
    from itertools import product

    rng = np.random.default_rng(2)
    u, moves, per = rng.normal(size=5), rng.normal(size=(2, 2)), np.array([3, 2])
    good, _, _ = quality.marginals(u, moves, per)
    weight = {s: np.exp(sum(u[i] * s[i] for i in range(3)) + sum(moves[a, b] for a, b in zip(s, s[1:]))) for s in product((0, 1), repeat=3)}
    assert good[1] == pytest.approx(sum(w for s, w in weight.items() if s[1]) / sum(weight.values()))


def test_long_texts_are_scored_like_short_ones():
    rng = np.random.default_rng(3)
    for n in (9, 10, 16, 50, 1003):
        u, moves = rng.normal(size=n) * 3, rng.normal(size=(2, 2)) * 2
        assert np.allclose(quality.marginals_of_long(u, moves), quality.marginals(u, moves, np.array([n]))[0])
    chain = quality.fit([("Clean words are here.\nAnd more of them.", 1), ("# $ a a a a\n# $\n# $", 0)] * 20)
    lines = ["Clean words are here.", "# $ a a a a", "", "x", "x", "Ünï, code."]
    texts = ["\n".join(lines[int(i)] for i in rng.integers(0, 6, n)).encode() for n in (1, 3, 200)] + [b"", b"\n", b"\n" * 50]
    assert np.allclose(quality.score_texts(texts, chain), [quality.score_long(t, chain, piece=40) for t in texts])
    import time

    began = time.process_time()
    assert 0 <= quality.score_texts([b"\n" * 300_000 + b"x"], chain)[0] <= 1
    assert time.process_time() - began < 30


def test_classifiers_edges():
    chain = quality.fit([("clean words here.", 1)])
    assert np.allclose(quality.score_texts([b"", b"a\n\nb"], chain), 0.5)
    model = toxicity.fit([("fine", 0)])
    assert toxicity.above([b"", b"x"], model).shape == (2, 3)
    rows = [("you idiot and fool", 1), ("a nice day in town", 0)] * 40
    over = toxicity.above([b"you idiot and fool", b"nice town", b""], toxicity.fit(rows))
    assert over[0, 0] > 0.5 > over[1, 0] and (np.diff(over, axis=1) <= 0).all()


def test_statistics_edges(spark):
    rows = [(1, None), (2, ""), (3, "a b\na b\n\n"), (4, "x # y"), (5, "p q r s t p q r s t u")]
    docs = spark.createDataFrame(rows, DOCS).withColumns({"lang": F.lit(None).cast("string"), "source": F.lit("s")})
    got = {r.doc_id: r for r in rules.statistics(docs).collect()}
    assert got[1].n_words == got[2].n_words == 0 and got[3].n_dup_lines == 1 and got[4].n_symbols == 1 and got[5].n_repeat_words == 10


def test_every_word_before_is_a_context(spark):
    rng = random.Random(4)
    vocabulary = [f"w{i}" for i in range(30)]
    texts = [" ".join(rng.choice(vocabulary) for _ in range(rng.randint(0, 40))) for _ in range(60)] + [None, "never seen words"]
    parts = pitman_yor.chunks(spark.createDataFrame(list(enumerate(texts)), DOCS).repartition(3), chunk_bytes=1500)
    held = {i: zlib.crc32(str(i).encode()) % 10 == 0 for i in range(len(texts))}
    walk = lambda i: list(zip([" ", *(texts[i] or "").split()], [*(texts[i] or "").split(), ""]))
    want = Counter(pair for i in held if not held[i] for pair in walk(i))
    name = lambda w: int(pitman_yor.names_of([w.encode()])[0, 0])
    m = pitman_yor.fit(parts, per_bucket=300)
    assert m.buckets > 2
    words = {r.g: r for r in m.words.collect()}
    by_name = {r.id: r for r in words.values()}
    counted, tables = Counter(), {}
    for r in m.blocks.collect():
        for key, n in zip(pitman_yor.unpack_keys(r.steps, r.dishes).tolist(), pitman_yor.unpack(r.n).tolist()):
            counted[words[key >> 32].id, words[key & 0xFFFFFFFF].id] += n
    assert +counted == {(name(a), name(b)): n for (a, b), n in want.items()}
    for r in m.seating.where("steps is not null").collect():
        for key, total in zip(pitman_yor.unpack_keys(r.steps, r.dishes).tolist(), pitman_yor.unpack(r.total).tolist()):
            tables[words[key >> 32].id, words[key & 0xFFFFFFFF].id] = total / 2
    assert set(tables) == {(name(a), name(b)) for (a, b), n in want.items() if n > 1}
    assert all(1 <= tables[name(a), name(b)] <= n for (a, b), n in want.items() if n > 1)
    assert sum(r.followers > 0 for r in words.values()) == len({a for a, _ in want}) > 8
    assert all(sum(r[f"p{j}"] for r in words.values() if r.n) + m.unknown[j] == pytest.approx(1) for j in (0, 1))
    for a in {a for a, _ in want}:  # a context's tables are those of its pairs
        assert sum(by_name[name(a)][f"k{j}"] for j in (0, 1)) / 2 == pytest.approx(sum(tables.get((name(x), name(y)), 1) for x, y in want if x == a))

    def prob(a, b):
        here, dish, n = by_name.get(name(a)), by_name.get(name(b)), want[a, b]
        out = n - 0.5 * tables.get((name(a), name(b)), min(n, 1))
        for j in (0, 1):
            out += (1 + 0.5 * (here[f"k{j}"] if here else 0)) * (dish[f"p{j}"] if dish else m.unknown[j]) / 2
        return out / (1 + (here.followers if here else 0))

    got = {r.doc_id: r for r in pitman_yor.score_chunks(parts, pitman_yor.answers(m), m).collect()}
    assert len(got) == len(texts)
    for i in held:
        assert got[i].score == pytest.approx(sum(np.log10(prob(a, b)) for a, b in walk(i))) and got[i].n_tokens == len(walk(i))


def test_outliers_beyond_usual_limits_are_rejected(spark):
    rng = random.Random(6)
    base = [(n := int(rng.lognormvariate(6, 0.6)) + 20, int(n * rng.uniform(4.7, 5.3)), 0, n // 20 + 2, 0, n // 100) for _ in range(300)]
    odd = {1000: (400, 2000, 60, 20, 0, 0), 1001: (400, 2000, 200, 20, 0, 0), 1002: (400, 2000, 0, 20, 12, 0), 1003: (400, 2000, 4, 20, 1, 8)}
    rows = [(i, "en", "s", *x) for i, x in [*enumerate(base), *odd.items()]]
    stats = spark.createDataFrame(rows, "doc_id long, lang string, source string, n_words long, word_chars long, n_symbols long, n_lines long, n_dup_lines long, n_repeat_words long")
    kept = {r.doc_id: r.kept for r in rules.apply_rules(stats).collect()}
    assert [kept[i] for i in odd] == [False, False, False, True]
    assert sum(kept[i] for i in range(300)) >= 290


def test_equal_rows_stay_apart_whatever_the_blocks(spark):
    bench = spark.createDataFrame([(i, f"w{i} x y z") for i in range(6)], "item_id long, text string")
    docs = spark.createDataFrame([(1, "w1 x y z w2 x y z")] * 3 + [(None, "w3 x y z")] * 2 + [(2, None)] * 2, DOCS)
    for block in (2_000_000, 2):
        got = Counter((r.doc_id, r.n_words, len(r.hit), ",".join(r["items"])) for r in decontaminate.find_leaks(docs, bench, block_words=block).collect())
        assert got == {(1, 8, 8, "1,2"): 3, (None, 4, 4, "3"): 2, (2, 0, 0, ""): 2}


def test_shared_ids_do_not_hide_links(spark):
    text = lambda i, end="": " ".join(f"t{i}w{j}" for j in range(60)) + end
    for shared in (7, None):
        rows = [(shared, text(i)) for i in range(8)] + [(100 + i, text(i, " end")) for i in range(8)]
        pairs = spark.createDataFrame(rows, DOCS)
        classes = jaccard.profiles(pairs, 5).groupBy(F.col("d1").alias("cls")).agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), *[F.first(f"p{i}").alias(f"p{i}") for i in range(jaccard.BITMAPS)]).persist()
        name = lambda t: int(jaccard.Sets([t.encode()], 5).digests()[0][0])
        links = [(name(text(i)), name(text(i, " end"))) for i in range(8)]
        similar = jaccard.similar_pairs(spark.createDataFrame(links, "a long, b long"), classes, pairs, 5, 80)
        assert {(r.a, r.b) for r in similar.collect()} == set(links)


def test_white_space_before_a_space_and_names_in_order():
    """The looks at single characters find what the pattern finds; runs of names are those of np.unique."""
    import re

    from simsearch.llm.encoding import _runs, unsafe

    white = [chr(c) for c in range(0x110000) if chr(c).isspace()]
    for t in ["", " ", "a b", "a  b", "é\n b", "\n", " \n", "一 　", *[w + " x" for w in white], *["x" + w for w in white], *[" " + w + "y" for w in white]]:
        assert unsafe(t) == bool(re.search(r"\s ", t)), repr(t)
    names = np.array([5, 3, 5, 1 << 63, 3, 0], np.uint64)
    found, place, number = _runs(names)
    assert (found == np.unique(names)).all() and (names[place] == found).all() and (found[number] == names).all()
    assert [len(x) for x in _runs(names[:0])] == [0, 0, 0]


def test_sets_of_much_text_take_little_memory():
    """Texts of a batch are worked on about a MB at a time (before, 4 MB: some 60 bytes of arrays a byte of text, for each worker)."""
    import tracemalloc

    import pyarrow as pa

    rng = np.random.default_rng(1)
    texts = [" ".join(map(str, rng.integers(0, 1 << 30, 20_000).tolist())) for _ in range(20)]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], names=["text"])
    bands, n = jaccard.Bands(80), 0
    tracemalloc.start()
    for piece in jaccard.pieces([batch]):
        sets = jaccard.Sets(common.utf8(piece.column("text").to_pylist()), 5)
        bands.signatures(sets, np.ones(piece.num_rows, bool))
        n += piece.num_rows
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert n == len(texts) and peak < 120 << 20


def test_pairs_of_a_chunk_take_little_memory():
    """Pairs of words are numbered with few arrays of a chunk's size (before, more than 60 bytes a token)."""
    import tracemalloc

    import pyarrow as pa

    rng = np.random.default_rng(1)
    codes, size = rng.integers(0, 300_000, 1_000_000).astype(np.uint32), 1000
    rows = pa.table({"at": [0], "ids": [list(range(1000))], "held_out": [[False] * 1000], "sizes": [[size] * 1000], "words": [pitman_yor.pack(codes)]})
    tracemalloc.start()
    pairs, number = pitman_yor.numbered(codes * np.int64(300_001))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    want, place = np.unique(codes, return_inverse=True)
    assert (pairs == want * np.int64(300_001)).all() and (number == place).all() and peak < 40 * len(codes)
    texts = pitman_yor.Texts(rows, np.full(300_001, -1), 1)
    before = np.concatenate((np.full((1000, 1), 300_000), codes.reshape(1000, size)[:, :-1]), axis=1).ravel()
    assert (texts.word[texts.number] == codes).all() and (texts.ctx[texts.number] == before).all()
