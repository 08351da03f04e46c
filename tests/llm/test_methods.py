"""Operators against brute force, exact round trips and held-out accuracy."""

import collections
import math
import random

import numpy as np
import pytest

from probgraph.llm import decontamination, induced_sort, mixing, near_dedup, passages, quality_classifier, quality_rules, substring_dedup, suffix_dedup, token_counts
from probgraph.llm import queries as q
from probgraph.llm.text import Codes, grams, words
from tests.conftest import duck, rows


@pytest.fixture(scope="module")
def texts(sf):
    return duck(sf).execute("select doc_id, text from documents order by doc_id").fetchall()


@pytest.mark.parametrize("name", sorted(q.ORACLE))
def test_sql(spark, sf, name):
    assert rows(q.QUERIES[name](spark, sf)) == rows(duck(sf).execute(q.ORACLE[name]).df())


def test_tokens_equal_a_unigram_tokenizer(texts):
    """The vocabulary as a unigram model of the public library gives the same counts."""
    import sentencepiece as sp
    from sentencepiece import sentencepiece_model_pb2 as pb

    model = pb.ModelProto()
    model.ParseFromString(open(token_counts.VOCAB, "rb").read())
    scores = token_counts.pieces(token_counts.VOCAB)
    model.trainer_spec.model_type = 1
    for p in model.pieces:
        if p.piece in scores and p.type == 1:
            p.score = scores[p.piece]
    known = sp.SentencePieceProcessor(model_proto=model.SerializeToString())
    trie = token_counts.ForwardTrie(scores)
    bag = sorted({w for _, t in texts for w in t.split()})
    bag = [w for w in bag if all(c in trie.vocab for c in w)][:4000]
    wrong = [w for w in bag if len(known.encode(w)) != trie.tokens(token_counts.MARK + w)]
    assert len(bag) > 500 and len(wrong) <= len(bag) // 500, wrong[:5]


def test_forward_scores(texts):
    trie = token_counts.ForwardTrie(token_counts.pieces(token_counts.VOCAB), max_nodes=500)

    def brute(w):
        best = [(0.0, 0)]
        for i in range(1, len(w) + 1):
            c = [(best[j][0] - trie.vocab[w[j:i]] if w[j:i] in trie.vocab else math.inf, best[j][1] + 1) for j in range(max(0, i - trie.longest), i)]
            if w[i - 1] not in trie.vocab:
                c.append((best[i - 1][0] - trie.lowest, best[i - 1][1] + len(w[i - 1].encode())))
            best.append(min(c))
        return best[-1][1]

    some = random.Random(1).sample(sorted({w for _, t in texts for w in t.split()}), 800) + ["☃☃a", "", "𝔘x"]
    assert [trie.tokens("▁" + w) for w in some] == [brute("▁" + w) for w in some]


def test_water_filling(spark):
    r = random.Random(5)
    for _ in range(6):
        sizes = {f"s{i}": r.randint(1, 400) for i in range(8)}
        weights = {k: r.choice([0.5, 1, 2, 5, 9]) for k in sizes}
        cap, budget = r.choice([1.0, 2.5, 4.0]), r.choice([0.5, 1.0, 2.0, 9.0])
        df = spark.createDataFrame([(i, "x" * n, k) for i, (k, n) in enumerate(sizes.items())], "doc_id long, text string, source string")
        got = {x.source: x.epochs for x in mixing.allocation(df, weights, cap, budget).collect()}
        # clamp and redistribute until nothing is over
        left, free, out = budget * sum(sizes.values()), set(sizes), {}
        while free:
            total = sum(weights[k] for k in free)
            over = {k for k in free if left * weights[k] / total > cap * sizes[k] + 1e-9}
            if not over:
                out |= {k: left * weights[k] / total for k in free}
                break
            for k in over:
                out[k] = cap * sizes[k]
            left -= sum(out[k] for k in over)
            free -= over
        assert all(abs(got[k] - out[k] / sizes[k]) < 1e-6 for k in sizes)


def test_induced_sorting(tmp_path):
    rng = np.random.default_rng(0)
    for it in range(200):
        n, a = int(rng.integers(1, 60)), int(rng.integers(1, 6))
        t = rng.integers(0, a, n)
        if rng.random() < 0.3:
            t = np.tile(t[: max(1, n // 4)], 5)
        b = t.tolist()
        sa = sorted(range(len(b)), key=lambda i: b[i:])
        lcp = [0]
        for x, y in zip(sa, sa[1:]):
            k = 0
            while max(x, y) + k < len(b) and b[x + k] == b[y + k]:
                k += 1
            lcp.append(k)
        for base, cap in ((1 << 26, 99), (1, 99), (4, 3)):  # base 1: the recursion goes down to the end
            got = induced_sort.suffix_arrays(t, cap, 3000 if it % 10 == 0 else 1 << 20, str(tmp_path), base)
            assert got[0].tolist() == sa and got[1].tolist() == [min(cap, x) for x in lcp]
    assert not list(tmp_path.glob("*"))


def brute_passages(docs, length):
    codes, seen, out = Codes(), {}, []
    for i, w in sorted({(i, tuple(words(t, codes).tolist())) for i, t in docs}):
        mark = [False] * (len(w) + 1)
        for s in range(len(w) - length + 1):
            if w[s : s + length] in seen:
                mark[s : s + length] = [True] * length
            else:
                seen[w[s : s + length]] = i
        at = None
        for x, m in enumerate(mark):
            if m and at is None:
                at = x
            if not m and at is not None:
                out.append((i, at, x))
                at = None
    return sorted(out)


def test_passages(spark, sf, texts):
    want = brute_passages(texts, 50)
    for name in ("op4_suffix_dedup", "op6_substring_dedup"):
        assert sorted((r.doc_id, r.start_word, r.end_word) for r in q.QUERIES[name](spark, sf).collect()) == want


def test_long_texts_are_cut_in_pieces(monkeypatch):
    code = np.random.default_rng(2).integers(1, 9, 4000).astype(np.uint64)
    whole = passages.cuts(code, 20, 4)
    monkeypatch.setattr(passages, "_PIECE", 1 << 9)
    part = passages.cuts(code, 20, 4)
    cover = lambda c: [(int(h), s + i) for h, s, n in zip(*c) for i in range(int(n))]
    assert sorted(cover(whole)) == sorted(cover(part)) and len(cover(whole)) == 4000 - 19


def test_grams():
    a = np.array([1, 2, 3, 1, 2, 3, 9, 1, 2, 3], np.uint64)
    for k in range(1, 11):
        g = grams(a, k)
        assert len(g) == len(a) - k + 1
        assert all((g[i] == g[j]) == (a[i : i + k].tolist() == a[j : j + k].tolist()) for i in range(len(g)) for j in range(len(g)))


def test_near_duplicates(spark, sf, texts):
    codes = Codes()
    sets = {i: near_dedup.shingles(words(t, codes)) for i, t in texts}
    by = collections.defaultdict(list)
    for i, s in sets.items():
        for x in s.tolist():
            by[x].append(i)
    shared = collections.Counter((b, a) for m in by.values() for n, a in enumerate(m) for b in m[:n])
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    inside = set()
    for (a, b), n in shared.items():
        low, high = sorted((len(sets[a]), len(sets[b])))
        if high <= near_dedup.RATIO * low and n >= near_dedup.THRESHOLD * low:
            if n >= near_dedup.THRESHOLD * high:
                up[root(a)] = root(b)
            elif low >= near_dedup.LEAST:
                inside.add(a if len(sets[a]) < len(sets[b]) else b)
    groups = collections.defaultdict(list)
    for i in sets:
        groups[root(i)].append(i)
    want = inside | {i for g in groups.values() for i in g if i != max(g, key=lambda i: (len(sets[i]), -i))}
    got = {r.doc_id for r in q.QUERIES["op5_near_dedup"](spark, sf).collect()}
    assert got <= want and len(got) >= 0.9 * len(want) and want


def test_contained_in_far_larger_texts(spark):
    """A text goes for one of any size that holds it; one that holds too little of it doesn't count."""
    rng = np.random.default_rng(5)
    word = lambda n: [f"w{x}" for x in rng.integers(0, 10**6, n)]
    small = [word(n) for n in (12, 20, 60, 300) for _ in range(10)]
    docs = [(i, " ".join(w)) for i, w in enumerate(small)]
    docs += [(100 + i, " ".join(word(3 * len(w)) + w + word(r * len(w)))) for i, (w, r) in enumerate(zip(small, [1, 10, 40] * 14))]
    docs += [(200, " ".join(word(900) + small[-1])), (201, None), (300, " ".join(alone := word(100))), (301, " ".join(alone[:50] + word(900)))]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r.doc_id for r in near_dedup.near_dedup(df).collect()}
    assert got == set(range(40))
    assert not {r.doc_id for r in near_dedup.near_dedup(df, ratio=2.5).collect()}


def test_classes_end_at_texts_that_stay(spark):
    """A text that goes for one that itself goes is in the class of what stays in the end; every document has a class."""
    word = lambda kind, n: [f"{kind}{x}" for x in range(n)]
    a, b = word("a", 40), word("b", 400)
    texts = {1: a, 2: a + b, 3: b + word("c", 600), 4: word("d", 30), 5: [], 7: word("d", 30), 8: b + word("c", 600) + ["e"]}
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in texts.items()] + [(6, None), (4, " ".join(a))], "doc_id long, text string")
    assert sorted(tuple(r) for r in near_dedup.near_dedup(docs).collect()) == [(1, 8), (2, 8), (3, 8), (4, 8), (7, 4)]
    assert sorted(tuple(r) for r in near_dedup.classes(docs).collect()) == [(1, 8), (2, 8), (3, 8), (4, 4), (4, 8), (5, 5), (6, 6), (7, 4), (8, 8)]


def test_memory_of_a_block():
    """Bytes a symbol while a block with repeats of thousands of words is indexed."""
    import tracemalloc

    rng = np.random.default_rng(3)
    base, parts = rng.integers(2, 60_000, 9_000), []
    for k in range(60):
        a = rng.integers(0, 5_000)
        parts += [base[a : a + 4_000], rng.integers(2, 60_000, 30), [(1 << 20) + k]]
    text = np.concatenate(parts).astype(np.int64)
    tracemalloc.start()
    substring_dedup.Block(text, 4_031)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 130 * len(text), peak / len(text)


def test_boilerplate_forms_no_pairs(spark, monkeypatch):
    """Passages that many texts share: only texts that are held meet far larger ones, and each meets its largest holder, however short the part of a list that is read at a time."""
    monkeypatch.setattr(near_dedup, "SAMPLE", 1)
    word = lambda kind, i, n: [f"{kind}{i}x{k}" for k in range(n)]
    shared, other = word("s", 0, 60), word("o", 0, 60)
    large = {i: shared + word("l", i, 400 + i) + (other if i % 3 == 0 else []) for i in range(40)}
    small = {100 + i: shared + word("m", i, 60) for i in range(40)}
    held = {200: shared, 201: word("l", 7, 407)[:90] + shared[:20], 202: shared[:45] + other[:45], 203: other[:40]}
    texts = {k: " ".join(v) for k, v in (large | small | held).items()}
    every = near_dedup.sketches(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).cache()
    nodes = every.select("node", "n")
    doc = {r.node: r.doc for r in every.select("node", "doc").collect()}
    for first in (2, 64):
        found = near_dedup.far_pairs(every, nodes, nodes.select("node").limit(0), 0.7, float("inf"), 0.95, 10, first=first).collect()
        assert len(found) < 400  # 40 times 40 pairs share the passage
        best = {}
        for r in sorted(found, key=lambda r: r.nb):
            if r.shared >= 0.7 * r.na:
                best[doc[r.a]] = doc[r.b]
        assert best == {200: 39, 201: 7, 202: 39, 203: 39}
    for n, kept, k in ((100, 70, near_dedup.tries(100, 70, 0.01)), (20, 3, near_dedup.tries(20, 3, 0.01)), (30, 1, near_dedup.tries(30, 1, 0.0))):
        assert math.comb(n - kept, k) <= max(0.01 * math.comb(n, k), 0)


def test_common_passages_form_no_candidates(spark, monkeypatch):
    """Texts of which larger ones have half, a common passage, aren't checked against these; those that one somewhat larger holds still go for it."""
    word = lambda kind, i, n: [f"{kind}{i}x{k}" for k in range(n)]
    shared = word("s", 0, 16)
    texts = {i: shared + word("l", i, 12) for i in range(10)} | {100 + i: shared + word("l", 100 + i, 34) for i in range(100)}
    texts |= {2000: word("t", 0, 40) + word("u", 0, 24), 2001: word("t", 0, 40), 2002: word("v", 0, 30), 2003: word("v", 0, 30) + ["w1"]}
    monkeypatch.setattr(near_dedup, "SAMPLE", 1)
    checked, pairs = near_dedup.checked, []

    def seen(candidates, every):
        pairs.append(candidates.count())
        return checked(candidates, every)

    monkeypatch.setattr(near_dedup, "checked", seen)
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in texts.items()], "doc_id long, text string")
    assert {tuple(r) for r in near_dedup.near_dedup(docs).collect()} == {(2001, 2000), (2002, 2003)}
    assert sum(pairs) < 150  # ten texts share the passage with a hundred larger ones
    for n, kept, need in ((100, 70, 2), (20, 3, 2), (14, 10, 2)):
        k = near_dedup.tries(n, kept, 0.01, need)
        assert sum(math.comb(kept, j) * math.comb(n - kept, k - j) for j in range(need)) <= 0.01 * math.comb(n, k)


def test_banding():
    for apart in range(near_dedup.furthest() + 1):
        r, b = near_dedup.banding(apart)
        s = near_dedup.jaccard_threshold(apart)
        assert r * b <= near_dedup.HASHES and 1 - (1 - s**r) ** b >= near_dedup.RECALL


def test_edit_distance_and_recall():
    rng = np.random.default_rng(1)

    def distance(p, t):
        prev = list(range(len(p) + 1))
        for x in t:
            cur = [prev[0] + 1]
            for j, y in enumerate(p):
                cur.append(min(prev[j + 1] + 1, cur[-1] + 1, prev[j] + (x != y)))
            prev = cur
        return prev[-1]

    for _ in range(150):
        p, t = rng.integers(1, 4, rng.integers(1, 8)).astype(np.uint64), rng.integers(1, 4, rng.integers(0, 13)).astype(np.uint64)
        e, s, f = decontamination.best_run(p, t)
        runs = [distance(p.tolist(), t[a:b].tolist()) for a in range(len(t) + 1) for b in range(a, len(t) + 1)]
        assert e == min(runs) == distance(p.tolist(), t[s:f].tolist())
    items = [(i, " ".join(f"w{x}" for x in rng.integers(0, 500, n))) for i, n in enumerate(rng.integers(12, 60, 40))]
    index = decontamination.Index(items)
    hit = total = 0
    for at, (i, w) in enumerate(index.items):
        for _ in range(5):
            x = w.tolist()
            for _ in range(index.d[at]):
                k, pos, new = rng.integers(3), int(rng.integers(len(x))), int(rng.integers(1, 2**62))
                x[pos : pos + (k != 1)] = [new] if k < 2 else []
            noise = lambda: rng.integers(1, 2**62, 50).astype(np.uint64)
            total += 1
            hit += any(g[1] == i for g in index.leaks([noise(), np.concatenate([noise(), np.array(x, np.uint64), noise()])]))
    assert hit / total >= 0.9


def test_leaks(spark, sf, texts):
    """Items that occur word for word are all found, in no other document."""
    codes = Codes()
    items = [(i, words(t, codes).tolist()) for i, t in duck(sf).execute("select item_id, text from benchmark").fetchall()]
    want = set()
    for d, t in texts:
        w = words(t, codes).tolist()
        line = ",".join(map(str, w)) + ","
        want |= {(d, i) for i, x in items if x and ("," + ",".join(map(str, x)) + ",") in "," + line}
    got = {(r.doc_id, r.item_id, r.edits) for r in q.QUERIES["op8_decontamination"](spark, sf).collect()}
    assert {g[:2] for g in got if g[2] == 0} == want


def test_classifier_held_out(spark):
    con = duck("/root/testdata/sf0.01")
    data = con.execute("select d.text, l.quality from documents d join labels l using (doc_id) order by doc_id").fetchall()
    w, b = quality_classifier.train([t for t, _ in data[::2]], [y for _, y in data[::2]])
    make = quality_classifier.Features()

    def score(t):
        i, v = make(t)
        return w[i] @ v + b

    right = [(score(t) > 0) == y for t, y in data[1::2]]
    assert sum(right) / len(right) > 0.95 and 0 < np.count_nonzero(w) < len(w)


def test_outliers(spark):
    """Planted outliers are rejected, the rest of a correlated cloud is kept; quantiles agree with tables."""
    assert abs(quality_rules.chi2_quantile(0.95, 6) - 12.5916) < 1e-3 and abs(quality_rules.chi2_quantile(0.5, 2) - 1.3863) < 1e-3
    con = duck("/root/testdata/sf0.01")
    data = con.execute("select d.doc_id, text, lang, source, quality from documents d join labels l using (doc_id)").fetchall()
    df = spark.createDataFrame([(r[0], r[1], r[2], r[3]) for r in data], "doc_id long, text string, lang string, source string")
    bad = {r.doc_id for r in quality_rules.judged(df).filter("rejected").collect()}
    good = {r[0] for r in data if r[4] == 1}
    assert not bad & good or len(bad & good) <= 0.01 * len(good)
    assert len(bad) >= 0.6 * (len(data) - len(good))


def test_concentration_steps_lower_the_determinant(spark):
    rng = np.random.default_rng(3)
    z = rng.normal(size=(900, 6)) @ np.diag([1, 2, 1, 3, 1, 1])
    z[:150] += 40
    df = spark.createDataFrame([("g", r.tolist()) for r in z], "g string, z array<double>")
    mean = np.array(quality_rules.estimates(df).first()["mean"])
    assert np.abs(mean).max() < 0.6


def test_blocks_equal_suffix_runs(spark):
    r = random.Random(8)
    vocab = [f"w{i}" for i in range(50)]
    shared = [" ".join(r.choices(vocab, k=80)) for _ in range(4)]
    docs = [(i, " ".join([" ".join(r.choices(vocab, k=r.randint(0, 60))), r.choice(shared)[r.randint(0, 40) :], " ".join(r.choices(vocab, k=20))])) for i in range(60)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    want = brute_passages(docs, 50)
    for f in (suffix_dedup.suffix_dedup, substring_dedup.substring_dedup):
        assert sorted((x.doc_id, x.start_word, x.end_word) for x in f(df).collect()) == want
