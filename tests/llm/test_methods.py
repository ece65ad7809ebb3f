"""The methods against brute force, round trips and held-out accuracy."""

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

import corpus_pipeline
from boundpath.llm import ctw, decontaminate, mixing, neardup, quality, registry, sharding, superminhash, textkernel, tokencount, toxicity, urlgraph
from boundpath.llm.components import connected_components
from boundpath.llm.shared import read_table

SF = "/root/testdata/sf0.001"
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def split(text):
    return [w for w in re.split(r"[\x20\x09-\x0D]+", (text or "").translate(LOW)) if w]


def sets(text, k):
    w = split(text)
    return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else frozenset()


def components(docs, k, num=80, den=100):
    """Smallest reachable id by comparing all pairs that share a shingle.  docs: (id, text)."""
    parent = {i: i for i, _ in docs}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    known = [(i, sets(t, k)) for i, t in docs]
    for a, (i, x) in enumerate(known):
        for j, y in known[:a]:
            both = len(x & y)
            if both and den * both >= num * (len(x) + len(y) - both):
                p, q = root(i), root(j)
                parent[max(p, q)] = min(p, q)
    return {i: root(i) for i in parent}, {i: len(s) for i, s in known}


def test_words_and_shingles():
    texts = ["Ab c  d\tAB x", None, "q", "", "é É z\n1 2 3 4 5", "tail", "tail"]
    got = [[w.text(i).decode() for i in range(len(w.hash))] for w in textkernel.words(pa.array(texts), limit=8)]
    assert sum(got, []) == sum(map(split, texts), [])
    w = next(textkernel.words(pa.array(texts)))
    doc, _, hashed = textkernel.shingles(w, 4)
    by = defaultdict(set)
    for d, h in zip(doc, hashed):
        by[d].add(h)
    assert {d: len(s) for d, s in by.items()} == {i: len(sets(t, 4)) for i, t in enumerate(texts) if split(t)}
    assert by[5] == by[6]


def test_superminhash_estimates():
    rng = np.random.default_rng(5)
    for n, similarity in ((3, 0.5), (40, 0.6), (400, 0.8), (3000, 0.9)):
        errors = []
        for _ in range(20):
            same = round(n * 2 * similarity / (1 + similarity))
            a = rng.integers(0, 1 << 52, n, dtype=np.uint64)
            b = np.concatenate([a[:same], rng.integers(0, 1 << 52, n - same, dtype=np.uint64)])
            s = superminhash.signatures(np.repeat([0, 1], n), np.concatenate([a, b]), 2)
            assert (s < 0xFFFFFFFF).all()
            errors.append((s[0] == s[1]).mean() - same / (2 * n - same))
        assert abs(np.mean(errors)) < 0.03 and np.std(errors) < 0.06
    one = superminhash.signatures(np.zeros(1, np.int64), np.array([7], np.uint64), 1)[0]
    assert sorted(one >> 25) == list(range(128))  # one element reaches every place once


def chained(rng, base, n):
    """Near copies of near copies."""
    out = [base]
    for _ in range(n):
        w = rng.choice(out).split()
        for _ in range(rng.randint(0, 3)):
            w[rng.randrange(len(w))] = f"z{rng.randrange(10**6)}"
        out.append(" ".join(w))
    return out


def test_near_duplicates_brute_force(spark):
    rng = random.Random(3)
    texts = []
    for g in range(6):
        texts += chained(rng, " ".join(f"g{g}v{rng.randrange(400)}" for _ in range(rng.randint(5, 90))), 40)
    texts += [t.upper() for t in texts[:10]] + ["", None, "one", "one", "two words"]
    rng.shuffle(texts)
    docs = list(enumerate(texts, 10))
    expected, sizes = components(docs, 4)
    out = neardup.near_duplicates(spark.createDataFrame(docs, "doc_id bigint, text string"), k=4).collect()
    assert {r.doc_id: r.component_id for r in out} == expected
    assert {r.doc_id: r.n_shingles for r in out} == sizes
    assert all(r.kept == (r.doc_id == r.component_id) for r in out)


def test_texts_of_one_id_keep_their_links(spark):
    """Rows of one doc_id with different texts: each text is compared as it is, and the document joins both groups."""
    rng = random.Random(11)
    prose = [" ".join(f"t{g}v{rng.randrange(300)}" for _ in range(60)) for g in range(4)]
    near = lambda t, n: " ".join([f"new{n}", *t.split()[1:]])
    rows = [(5, prose[0]), (5, prose[1]), (7, near(prose[0], 1)), (8, near(prose[1], 2)), (9, prose[2]), (3, near(prose[2], 3)), (11, prose[3]), (11, prose[3]), (5, prose[0]), (12, None)]
    out = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), k=4).collect()
    assert len(out) == len(rows)
    assert {r.doc_id: r.component_id for r in out} == {5: 5, 7: 5, 8: 5, 9: 3, 3: 3, 11: 11, 12: 12}


def test_common_shingles_are_dealt_over_cells(spark, monkeypatch):
    """The same components when each task of the prefix join sees few rows of a shingle."""
    rng = random.Random(6)
    texts = []
    for g in range(3):
        texts += chained(rng, " ".join(f"g{g % 2}v{rng.randrange(60)}" for _ in range(30)), 60)
    docs = list(enumerate(texts, 1))
    table = spark.createDataFrame(docs, "doc_id bigint, text string")
    want, _ = components(docs, 4)
    for cell in (1000, 5):
        monkeypatch.setattr(neardup, "CELL", cell)
        assert {r.doc_id: r.component_id for r in neardup.near_duplicates(table, k=4).collect()} == want


def test_components(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(200)] + [(rng.randrange(300, 500), rng.randrange(300, 500)) for _ in range(120)] + [(5, 5), (None, 3)]
    parent = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            p, q = root(a), root(b)
            parent[max(p, q)] = min(p, q)
    found = connected_components(spark.createDataFrame(edges, "u bigint, v bigint").repartition(7)).collect()
    assert {r.node: r.component for r in found} == {x: root(x) for x in parent}
    assert len(found) == len(parent)


def test_hamming_index():
    rng = np.random.default_rng(2)
    prints = rng.integers(0, 1 << 63, 60, dtype=np.uint64)
    queries = np.array([int(p) ^ sum(1 << int(b) for b in rng.choice(64, n, replace=False)) for p, n in zip(prints, rng.integers(0, 30, 60))], np.uint64)
    q, p = decontaminate.HammingIndex(prints).search(queries)
    near = {(i, j) for i in range(60) for j in range(60) if bin(int(queries[i]) ^ int(prints[j])).count("1") <= 19}
    assert set(zip(q.tolist(), p.tolist())) == near


def leaks(docs, items):
    """Best similarity of item-sized windows, all windows tried."""
    words = lambda t: re.findall(r"[a-z0-9\x80-\U0010ffff]+", (t or "").translate(LOW))
    bags = [(i, len(w), Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4))) for i, t in items if len(w := words(t)) >= 5]
    out = {}
    for d, t in docs:
        w = words(t)
        s = [tuple(w[j : j + 5]) for j in range(len(w) - 4)]
        for i, n, bag in bags:
            if not set(s) & set(bag):
                continue
            span = min(n - 4, len(s))
            best = max(decontaminate.bag_similarity(Counter(s[j : j + span]), bag) for j in range(len(s) - span + 1))
            if best >= 0.8:
                out[d, i] = best
    return out


def test_decontamination_brute_force(spark):
    rng = random.Random(4)
    items = [(i, " ".join(f"b{i}n{rng.randrange(200)}" for _ in range(rng.randint(20, 60)))) for i in range(12)]
    docs = []
    for d in range(60):
        w = [f"q{rng.randrange(900)}" for _ in range(rng.randint(0, 200))]
        if d % 2:
            leak = rng.choice(items)[1].split()
            for _ in range(rng.randrange(3)):
                leak[rng.randrange(len(leak))] = "edit"
            at = rng.randint(0, len(w))
            w[at:at] = leak if d % 6 else leak[2:]
        docs.append((d, " ".join(w).upper() if d % 5 == 0 else " , ".join(w)))
    out = decontaminate.contaminated(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string")).collect()
    got, want = {(r.doc_id, r.item_id): r.similarity for r in out}, leaks(docs, items)
    assert set(got) == set(want) and len(got) > 5
    assert all(abs(got[k] - want[k]) < 1e-12 for k in got)


def test_short_items_are_found_inside_documents(spark):
    """Items of fewer words than a shingle match just these words in a row, wherever they stand."""
    texts = ["we say to be or not to be in class", "to be or not", "to be or", "Not, to be: or. not", "be or not to", "x", "to be x or not"]
    items = [(0, "To be or not"), (1, "x"), (2, "in class"), (3, "to be or not to be in class we")]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    out = decontaminate.contaminated(docs, spark.createDataFrame(items, "item_id bigint, text string")).collect()
    assert {(r.doc_id, r.item_id) for r in out} == {(0, 0), (0, 2), (1, 0), (3, 0), (5, 1), (6, 1)}
    assert {r.doc_id: (r.first_word, r.n_windows, r.similarity) for r in out if r.item_id == 0} == {0: (2, 1, 1.0), 1: (0, 1, 1.0), 3: (1, 1, 1.0)}


def test_clean_documents_pass_the_sieve_whole(spark):
    docs = read_table(spark, SF, "documents")
    bench = read_table(spark, SF, "benchmark")
    hit = {r.doc_id for r in decontaminate.contaminated(docs, bench).collect()}
    for passes in (20_000, 11):
        rest = decontaminate.drop_contaminated(docs, bench, items_per_pass=passes)
        assert rest.schema == docs.schema
        assert sorted(map(str, rest.collect())) == sorted(str(r) for r in docs.collect() if r.doc_id not in hit)


def test_items_in_several_passes(spark):
    docs, bench = read_table(spark, SF, "documents"), read_table(spark, SF, "benchmark")
    one = {(r.doc_id, r.item_id, r.similarity) for r in decontaminate.contaminated(docs, bench).collect()}
    assert one == {(r.doc_id, r.item_id, r.similarity) for r in decontaminate.contaminated(docs, bench, items_per_pass=11).collect()}


def test_tokens_share_prefixes():
    v = tokencount.UnigramVocabulary.load(tokencount.default_model())
    words = sorted({tokencount.WORD_MARK + w for w in "the then there th t zebra zebras zeßra 漢字 \U0001f600x internationalisation".split()})
    assert v.count_sorted(words) == [v.count(w) for w in words]
    assert v.count(tokencount.WORD_MARK + "the") == 1
    small = tokencount.UnigramVocabulary({"a": -1.0, "b": -1.0, "ab": -1.5, "abc": -9.0})
    assert small.count("ab") == 1 and small.count("abab") == 2 and small.count("c") == 1 and small.count("abé") == 3


def test_token_counts_of_texts(spark):
    v = tokencount.UnigramVocabulary.load(tokencount.default_model())
    docs = read_table(spark, SF, "documents").select("doc_id", "text")
    want = {r.doc_id: sum(v.count(tokencount.WORD_MARK + w) for w in re.split(r"[\x20\x09-\x0D]+", r.text or "") if w) for r in docs.collect()}
    assert {r.doc_id: r.n_tokens for r in tokencount.count_tokens(docs).collect()} == want


def test_context_tree_by_definition():
    """A tree of depth 2 against the recursive definition, and probabilities that sum to one."""
    text = b"abracadabra alakazam abracadabra"
    w = next(textkernel.words(pa.array([text.decode()])))
    keys, _ = ctw.strings(w, 2)
    levels = []
    for d in range(3):
        k, n = np.unique(keys & np.uint64((1 << (8 * (d + 1))) - 1), return_counts=True)
        levels.append((k, n.astype(float)))
    tree = ctw.ContextTree(levels)
    counts = defaultdict(lambda: [0, 0])
    for key in keys.tolist():
        for d in range(3):
            context = (key >> 8) & ((1 << (8 * d)) - 1)
            for i in range(8):
                counts[d, context, (1 << i) | ((key & 255) >> (8 - i))][(key >> (7 - i)) & 1] += 1
    kt = lambda c: math.lgamma(c[0] + 0.5) + math.lgamma(c[1] + 0.5) - math.lgamma(sum(c) + 1) - math.log(math.pi)

    def weighted(d, context, q):
        own = kt(counts[d, context, q])
        if d == 2:
            return own
        deep = sum(weighted(d + 1, c, q) for (e, c, r) in list(counts) if e == d + 1 and r == q and c & ((1 << (8 * d)) - 1) == context)
        return np.logaddexp(own, deep) - math.log(2)

    def one(d, context, q):
        c = counts[d, context & ((1 << (8 * d)) - 1), q]
        here = (c[1] + 0.5) / (sum(c) + 1)
        if d == 2 or (d + 1, context & ((1 << (8 * d + 8)) - 1), q) not in counts:
            return here
        stop = math.exp(kt(c) - math.log(2) - weighted(d, context & ((1 << (8 * d)) - 1), q))
        return stop * here + (1 - stop) * one(d + 1, context, q)

    for key in {int(k) for k in keys[:12]}:
        p = 1.0
        for i in range(8):
            q, bit = (1 << i) | ((key & 255) >> (8 - i)), (key >> (7 - i)) & 1
            ones = one(0, key >> 8, q)
            p *= ones if bit else 1 - ones
        assert abs(tree.log10(np.array([key], np.uint64))[0] - math.log10(p)) < 1e-6
    every = (np.uint64(ord("a")) << np.uint64(16)) | (np.uint64(ord("b")) << np.uint64(8)) | np.arange(256, dtype=np.uint64)
    assert abs((10 ** tree.log10(every)).sum() - 1) < 1e-9


def test_scores(spark):
    from pyspark.sql import functions as F

    docs = read_table(spark, SF, "documents").select("doc_id", "text")
    out = {r.doc_id: r for r in registry.queries()["op2_lm_score"](spark, SF).collect()}
    rows = docs.collect()
    train = Counter()
    for r in rows:
        if zlib.crc32(str(r.doc_id).encode()) % 7 != 2:
            train.update(split(r.text) + [None])
    total, distinct = sum(train.values()), len(train)
    for r in rows:
        tokens = split(r.text) + [None]
        got = out[r.doc_id]
        base = sum(math.log10((train[t] + 1) / (total + distinct + 1)) for t in tokens)
        assert (got.n_tokens, got.n_known, got.train_tokens) == (len(tokens), sum(train[t] > 0 for t in tokens), total)
        assert abs(got.base_score - base) < 1e-6 * abs(base) and got.score < 0
    few = ctw.score_texts(docs, F.lit(False), rare_share=0.01).collect()  # nearly all words through the join
    many = ctw.score_texts(docs, F.lit(False)).collect()
    assert sum(r.n_known for r in few) == sum(r.n_known for r in many)
    assert abs(sum(r.base_score for r in few) - sum(r.base_score for r in many)) < 1e-3


def test_counts_of_a_side_that_is_empty():
    """Several chunks without a text held out, or without one to learn from, count nothing on that side."""
    for trains in (True, False):
        batches = [pa.RecordBatch.from_arrays([pa.array(["a b", "c"]), pa.array([trains, trains])], names=["text", "train"])] * 2
        kinds = {k for b in ctw._count(5)(batches) for k in b.column(0).to_pylist()}
        assert kinds == ({0, 1} if trains else {2})


def test_scores_use_every_context(spark):
    """Few broadcast prices and many small tasks change nothing: all contexts of the training texts count."""
    from pyspark.sql import functions as F

    rows = [(r.doc_id, r.text) for r in read_table(spark, SF, "documents").select("doc_id", "text").orderBy("doc_id").limit(40).collect()]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    held = F.col("doc_id") % 3 == 0
    w = next(textkernel.words(pa.array([t for i, t in rows if i % 3]), limit=1 << 30))
    keys, n = np.unique(ctw.strings(w, 5)[0], return_counts=True)
    tree = ctw.ContextTree(ctw.shorter(keys, n, 0, 5))
    want = {}
    for i, t in rows:
        want[i] = tree.log10(ctw.strings(next(textkernel.words(pa.array([t]), limit=1 << 30)), 5)[0]).sum()
    for more in ({}, {"entries": 300, "part": 2000}, {"entries": 0}):
        got = {r.doc_id: r.score for r in ctw.score_texts(docs, held, **more).collect()}
        assert got.keys() == want.keys()
        assert all(abs(got[i] - want[i]) < 1e-6 * abs(want[i]) + 1e-9 for i in want)


def histogram(sizes):
    return sorted(Counter(sizes).items(), reverse=True)


def plain_best_fit(sizes, capacity):
    """Loads of the bins, and the sizes in each: every item alone into the tightest bin, found by looking at all."""
    remaining, held = [], []
    for s in sorted(sizes, reverse=True):
        fits = [(r, b) for b, r in enumerate(remaining) if r >= s]
        if not fits:
            fits = [(capacity, len(remaining))]
            remaining.append(capacity)
            held.append([])
        b = min(fits)[1]
        remaining[b] -= s
        held[b].append(s)
    return held


def test_page_rank_by_dense_iteration(spark):
    """Ranks against the fixed point of the whole matrix; hosts without links out return their mass to the seeds."""
    rng, n = np.random.default_rng(8), 30
    edges = sorted({(int(a), int(b)) for a, b in rng.integers(0, n, (70, 2)) if a != b and a < 25})
    times = rng.integers(1, 5, len(edges)).astype(float)
    seed = np.zeros(n)
    seed[[0, 3, 9]] = [1.0, 2.0, 0.5]
    step = np.zeros((n, n))
    for (a, b), t in zip(edges, times):
        step[a, b] = t
    step /= np.maximum(step.sum(axis=1, keepdims=True), 1e-300)
    s = seed / seed.sum()
    want = s.copy()
    for _ in range(400):
        sent = 0.85 * want @ step
        want = sent + (1 - sent.sum()) * s
    table = spark.createDataFrame([(f"h{a}", f"h{b}", float(t)) for (a, b), t in zip(edges, times)], "src string, dst string, n double")
    seeds = spark.createDataFrame([(f"h{i}", float(w)) for i, w in enumerate(seed)], "host string, weight double")
    got = {r.host: r["rank"] for r in urlgraph.personalised_rank(table, seeds, tolerance=1e-5).collect()}
    assert sum(abs(got.get(f"h{i}", 0.0) - want[i]) for i in range(n)) <= 1e-5 and abs(sum(got.values()) - 1) < 1e-9


def test_best_fit_decreasing():
    """Packing the histogram is packing item by item."""
    rng = random.Random(7)
    for n in range(60):
        sizes = [rng.randint(1, rng.choice([6, 60])) for _ in range(rng.randint(1, 200))]
        runs, opened = sharding.best_fit_decreasing(histogram(sizes), 60)
        held = [[] for _ in range(opened)]
        for size, place, times in runs:
            held[place] += [size] * times
        assert held == plain_best_fit(sizes, 60)
        assert sharding.best_fit_decreasing(histogram(sizes), 60, opened - 1) is None
    assert sharding.best_fit_decreasing([(61, 1)], 60) is None


def test_remaining_tree():
    rng, tree, plain = random.Random(3), sharding.RemainingTree(), []
    for i in range(4000):
        if rng.random() < 0.6 or not plain:
            plain.append((rng.randrange(500), i))
            tree.add(*plain[-1])
        else:
            size = rng.randrange(520)
            want = min((x for x in plain if x[0] >= size), default=None)
            assert tree.take_tightest(size) == want
            plain = [x for x in plain if x != want]

    def check(node):
        if node is None:
            return 0
        left, right = check(node.left), check(node.right)
        assert abs(left - right) <= 1
        return 1 + max(left, right)

    assert check(tree._root) < 16


@pytest.mark.parametrize("case", ["even", "one giant", "few", "ties"])
def test_equal_shards(case):
    rng = random.Random(5)
    sizes = {"even": [rng.randint(17, 4000) for _ in range(3000)], "one giant": [10**7] + [rng.randint(17, 900) for _ in range(900)], "few": [5, 3], "ties": [40] * 801}[case]
    loads, n = Counter(), Counter()
    for size, place, times in sharding.pack_equal(histogram(sizes), 40):
        loads[place] += size * times
        n[size] += times
    assert n == Counter(sizes) and set(loads) <= set(range(40))
    if case == "even":
        assert max(loads.values()) - min(loads.values()) <= 40
    if case == "one giant":
        rest = sorted(loads.values())[:-1]
        assert max(loads.values()) == 10**7 and len(loads) == 40 and rest[-1] - rest[0] <= 100
    if case == "ties":
        assert max(loads.values()) == 21 * 40


def sharded(spark, texts, **how):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    return sharding.shard_documents(docs, **how).toPandas()


def test_sharding(spark):
    out = registry.queries()["op4_sharding"](spark, SF).toPandas()
    groups = out.groupby("text_crc32")["size"].sum()
    want = Counter()
    for size, place, times in sharding.pack_equal(histogram(groups.tolist()), 40):
        want[place] += size * times
    assert out.groupby("shard")["size"].sum().to_dict() == dict(want)  # the query's loads are those of the packing
    for _, part in out.groupby("shard"):
        assert sorted(part.slot) == list(range(len(part)))
    assert out.groupby("text_crc32").shard.nunique().max() == 1
    texts = [r.text or "" for r in read_table(spark, SF, "documents").collect()]
    assert Counter(out["size"]) == Counter(len(t.encode()) + 16 for t in texts)


def test_fixed_capacity(spark):
    """Shards of a capacity hold what item by item packing puts there; many small groups never overflow one."""
    rng = random.Random(2)
    texts = ["x" * rng.randint(0, 300) + str(i % 700) for i in range(1500)] + ["same text"] * 300 + ["y" * 9000] * 2
    for how in ({}, {"most_bins": 40}):
        out = sharded(spark, texts, shards=None, capacity=3000, **how)
        loads, groups = out.groupby("shard")["size"].sum(), out.groupby("text_crc32")["size"].sum()
        over = groups[groups > 3000]
        assert sorted(loads[loads > 3000]) == sorted(over) and len(over) == 2  # groups beyond the capacity stand alone
        assert out.groupby("text_crc32").shard.nunique().max() == 1
        assert sorted(loads.index) == list(range(len(loads)))
        alone = plain_best_fit([s for s in groups if s <= 3000], 3000)
        if not how:
            assert sorted(loads[loads <= 3000]) == sorted(map(sum, alone))
        else:
            assert len(loads) <= len(alone) + 2 + 5
    assert sharded(spark, [], shards=None, capacity=10).empty


def water_fill(caps, weights, total):
    """Shares of ``total`` by weight, none above its cap: shares above are set to their caps and the rest is dealt anew."""
    target, open_, left = [0.0] * len(caps), [i for i, c in enumerate(caps) if c > 0 and weights[i] > 0], float(total)
    while open_:
        unit = left / sum(weights[i] for i in open_)
        over = [i for i in open_ if unit * weights[i] > caps[i]]
        for i in over or open_:
            target[i] = float(caps[i]) if over else unit * weights[i]
            left -= caps[i] if over else 0.0
        open_ = [i for i in open_ if i not in over] if over else []
    return target


def test_targets(spark):
    for sizes in ([10, 100, 1000], [0, 5, 7], [4], [3, 900, 5, 5, 100000, 1], [0, 0], [50] * 9):
        names = [None if i == 1 else chr(97 + i) for i in range(len(sizes))]
        order = sorted(range(len(sizes)), key=lambda i: (names[i] is None, names[i] or ""))
        weights = dict(zip(order, (5, 2, 1) * len(sizes)))
        want = water_fill([3 * s for s in sizes], [weights[i] for i in range(len(sizes))], sum(sizes))
        got = {r.source: (r.source_size, r.target) for r in mixing.source_targets(spark.createDataFrame(list(zip(names, sizes)), "source string, size bigint")).collect()}
        assert all(got[n][0] == s and abs(got[n][1] - w) < 1e-6 * max(1, w) for n, s, w in zip(names, sizes, want))


def test_mixing(spark):
    rows = registry.queries()["op9_mixing"](spark, "/root/testdata/sf0.01").toPandas()
    again = registry.queries()["op9_mixing"](spark, "/root/testdata/sf0.01").toPandas()
    assert rows.sort_values("doc_id").reset_index(drop=True).equals(again.sort_values("doc_id").reset_index(drop=True))
    assert (rows.taken <= 3 * rows["size"]).all()
    for _, part in rows.groupby(["source_size", "target"]):
        assert abs(part.taken.sum() - part.target.iloc[0]) <= part["size"].max()


def test_mixing_by_plain_order_sampling(spark):
    """The copies of every document, by sorting each source's documents by their odds ratio and walking to the target."""
    from pyspark.sql import functions as F

    docs = read_table(spark, SF, "documents")
    u = mixing._unit(11, "doc_id", F.xxhash64("text"))
    rows = [(r.doc_id, r.source, len([w for w in re.split(r"[\x20\x09-\x0D]+", r.text or "") if w]), r.u) for r in docs.withColumn("u", u).collect()]
    names = sorted({r[1] for r in rows}, key=lambda n: (n is None, n or ""))
    sizes = [sum(r[2] for r in rows if r[1] == n) for n in names]
    targets = water_fill([3 * s for s in sizes], [(5, 2, 1)[i % 3] for i in range(len(names))], sum(sizes))
    want = {}
    for name, target in zip(names, targets):
        mine = [r for r in rows if r[1] == name and r[2]]
        pull = [2 ** (math.floor(math.log2(1 + r[2] / (r[2] + 100)) * 16) / 16) for r in mine]
        shares = water_fill([3 * r[2] for r in mine], [r[2] * w for r, w in zip(mine, pull)], target)
        assert abs(sum(shares) - target) < 1e-6 * target
        ranked, left = [], target
        for (i, _, size, x), share in zip(mine, shares):
            whole = math.floor(share / size + 1e-9)
            p = max(0.0, share / size - whole)
            want[i], left = whole, left - whole * size
            if p > 1e-6:
                ranked.append(((x / (1 - x)) / (p / (1 - p)), i, size))
        taken = 0
        for _, i, size in sorted(ranked):
            taken += size
            want[i] += taken - size / 2 <= left
    got = {r.doc_id: r.copies for r in mixing.mix(docs).collect()}
    off = [i for i in got if got[i] != want.get(i, 0)]
    assert len(got) == len(rows) and not off
    assert len(set(got.values())) > 2


def test_pareto_order_inclusion(spark):
    """Over seeds, documents enter as often as their inclusion probability says; weights shift it."""
    docs = spark.createDataFrame([(i, " ".join(["w"] * 10), "s" if i < 40 else "t", 2.0 if i % 2 else 1.0) for i in range(80)], "doc_id bigint, text string, source string, w double")
    from pyspark.sql import functions as F

    hits = Counter()
    for seed in range(12):
        for r in mixing.mix(docs, weights=(3, 1), seed=seed, weight=F.col("w")).collect():
            hits[r.source, r.doc_id % 2] += r.copies
    assert hits["s", 1] > hits["s", 0] and hits["t", 1] > 1.5 * hits["t", 0]
    assert abs(hits["s", 0] + hits["s", 1] - 12 * 60) <= 12 and abs(hits["t", 0] + hits["t", 1] - 12 * 20) <= 12


def test_quality_counts(spark):
    rows = registry.queries()["op5_quality"](spark, SF).toPandas().set_index("doc_id")
    for r in read_table(spark, SF, "documents").collect():
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", r.text or "") if x]
        runs = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        twice = Counter(runs)
        covered = {j for i, x in enumerate(runs) if twice[x] > 1 for j in range(i, i + 5)}
        lines = [x for x in (r.text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        got = rows.loc[r.doc_id]
        assert (got.n_words, got.word_chars, got.n_repeat_words, got.n_dup_lines) == (len(w), sum(map(len, w)), len(covered), len(lines) - len(set(lines)))


def test_cascade_order_and_verdict(spark):
    docs = read_table(spark, "/root/testdata/sf0.01", "documents")
    order = quality.estimate(docs)
    assert [e.rank for e in order] == sorted((e.rank for e in order), reverse=True) and {e.rule for e in order} == set(quality.RULES)
    kept = {r.doc_id for r in quality.filter_quality(docs).collect()}
    assert kept == {r.doc_id for r in registry.queries()["op5_quality"](spark, "/root/testdata/sf0.01").collect() if r.kept}


def test_toxicity_finds_the_sentence(spark):
    rng = random.Random(9)
    calm = [f"word{i}" for i in range(300)]
    sentence = lambda: " ".join(rng.choice(calm) for _ in range(8)) + "."
    texts, y, where = [], [], []
    for i in range(400):
        s = [sentence() for _ in range(6)]
        bad = i % 5 == 0
        at = rng.randrange(6)
        if bad:
            s[at] = s[at].replace(" ", " " + rng.choice(["vile", "nasty", "foul"]) + " ", 1)
        texts.append(" ".join(s))
        y.append(int(bad))
        where.append(at if bad else -1)
    model = toxicity.train(texts[:300], y[:300])
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    out = {r.doc_id: r for r in toxicity.score_toxicity(docs, model).collect()}
    held = range(300, 400)
    assert sum((out[i].score >= 0.3) == bool(y[i]) for i in held) >= 97
    assert sum(out[i].worst_sentence == where[i] for i in held if y[i]) >= 18


def test_settings_come_from_training_rows_alone(spark):
    """Held-out labels change nothing; folds and the final fit run in tasks and agree with the plain functions."""
    from pyspark.sql import functions as F

    sf = "/root/testdata/sf0.01"
    docs, labels = read_table(spark, sf, "documents"), read_table(spark, sf, "labels")
    held = F.coalesce(toxicity.fold("doc_id", 4) == 2, F.lit(False))
    other = labels.withColumn("toxic", F.when(held, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = (toxicity.fit(docs, t.filter(~held)) for t in (labels, other))
    assert np.array_equal(a.weights, b.weights) and a.bias == b.bias and a.prefixes == b.prefixes
    rows = toxicity.training_rows(docs, labels.filter(~held)).toArrow()
    texts, y = pa.array(rows["text"].to_pylist(), pa.string()), np.array(rows["toxic"].to_pylist())
    totals = (int((y == 0).sum()), int((y == 1).sum()))
    chosen, losses = toxicity.choose_setting(spark, spark.sparkContext.broadcast((texts, y)), totals)
    assert chosen.prefixes == a.prefixes and losses[chosen] == min(losses.values()) and len(losses) == 9
    assert abs(losses[chosen] - np.mean([toxicity.fold_loss(texts, y, totals, chosen, f) for f in range(3)])) < 1e-9
    small = toxicity.training_rows(docs, labels.filter(~held), max_docs=20, max_bytes=9000).toPandas()
    assert (small.groupby("toxic").size() <= 20).all() and (small.text.str.len().groupby(small.toxic).sum() <= 9000).all()


def test_toxicity_held_out(spark):
    out = registry.queries()["op6_toxicity"](spark, "/root/testdata/sf0.1").toPandas()
    labels = read_table(spark, "/root/testdata/sf0.1", "labels").toPandas()
    held = out[out.held_out].merge(labels, on="doc_id")
    bad, good = held[held.toxic == 1], held[held.toxic == 0]
    assert bad.predicted.mean() > 0.7 and good.predicted.mean() < 0.02


def test_pipeline_brute_force(spark):
    """Up to mixing, whose draw is a hash, every stage against plain code; then sizes, targets and shards."""
    docs = read_table(spark, SF, "documents")
    stages = dict(corpus_pipeline.STAGES)
    kept = {r.doc_id for r in registry.queries()["op5_quality"](spark, SF).collect() if r.kept}
    now = stages["quality_rules"](spark, docs, SF)
    assert {r.doc_id for r in now.collect()} == kept
    rows = sorted((r.doc_id, r.text) for r in now.collect())
    expected, _ = components(rows, 5)
    now = stages["near_dedup"](spark, now, SF)
    assert sorted(r.doc_id for r in now.collect()) == sorted(i for i in expected if expected[i] == i)
    rows = [(r.doc_id, r.text) for r in now.collect()]
    leaked = {d for d, _ in leaks(rows, [(r.item_id, r.text) for r in read_table(spark, SF, "benchmark").collect()])}
    now = stages["decontamination"](spark, now, SF)
    assert {r.doc_id for r in now.collect()} == {i for i, _ in rows} - leaked
    copies = {r.doc_id: r.copies for r in mixing.mix(now).collect()}
    now = stages["mixing"](spark, now, SF)
    assert Counter(r.doc_id for r in now.collect()) == Counter({i: n for i, n in copies.items() if n})
    out = stages["sharding"](spark, now, SF).toPandas()
    assert len(out) == sum(copies.values())
    for _, part in out.groupby("shard"):
        assert sorted(part.slot) == list(range(len(part)))
    assert corpus_pipeline.run(spark, SF).count() == len(out)


def test_signatures_in_small_chunks(monkeypatch):
    """A worker never has more than half a megabyte of texts in its arrays, and chunks change nothing."""
    texts = [" ".join(f"{i % 7}-{j}" for j in range(3000)) for i in range(100)]
    size = max(map(len, texts))
    batch = pa.RecordBatch.from_arrays([pa.array(range(100)), pa.array(range(100)), pa.array(texts)], names=["doc_id", "rkey", "text"])
    many = list(neardup._sign(5, 128, 4)([batch]))
    assert max(b.num_rows for b in many) * size <= 600_000
    monkeypatch.setattr(neardup, "CHUNK", 1 << 30)
    one = list(neardup._sign(5, 128, 4)([batch]))
    assert len(one) == 1 and pa.Table.from_batches(many).to_pylist() == one[0].to_pylist()


def test_near_dedup_leaves_texts_in_place(spark):
    """Where the ids that joins bring to the texts are few, no exchange holds a text of the documents, whatever their size."""
    docs = read_table(spark, SF, "documents")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        stage = corpus_pipeline.near_dedup(spark, docs, SF)
        own = docs.selectExpr("doc_id", "doc_id AS rkey", "text")
        texts = neardup._texts(own, own.select("rkey"), own.selectExpr("doc_id AS id", "rkey"))
        for df in (stage, texts):
            assert "SortMergeJoin" not in df._jdf.queryExecution().executedPlan().toString()
        assert texts.count() == docs.count()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_oracles(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    a = registry.queries()[name](spark, SF).toPandas()
    b = con.sql(registry.oracle_sql()[name]).df()[list(a.columns)]
    key = lambda df: sorted(map(str, df.astype(object).where(df.notna(), None).itertuples(index=False, name=None)))
    assert [re.sub(r"\.0\b", "", x) for x in key(a)] == [re.sub(r"\.0\b", "", x) for x in key(b)]
