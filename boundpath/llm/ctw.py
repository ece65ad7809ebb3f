"""Language-model scores by context-tree weighting over bytes.

A byte is eight binary decisions.  For every decision (a node of the byte's bit tree) a context tree over the preceding
bytes holds counts of zeros and ones; a Krichevsky-Trofimov estimate at each context is mixed with the product of its
children's weighted probabilities, half and half, from the deepest contexts up to none.  The posterior weights of
"stop here" along a path then mix the estimates of all depths into one prediction per decision, and the product over
decisions and bytes is the text's probability.  A text ends with byte 0xFF, which UTF-8 never uses, and starts after such
bytes, so probabilities sum to one over texts.

Counts are taken over all training bytes, and every context has its node: tasks count byte strings of depth + 1, Spark sums
them.  Strings whose contexts end with the same three bytes lie in one task, which holds the subtree below those bytes; the
driver holds contexts of up to two bytes (at most 2^24 strings, however large the corpus).  Tasks send up what the mixture
over their subtrees gives, the driver sends down what is settled above them, and tasks price every string that any text has.
Prices of the most frequent strings are broadcast, all others are joined.  Word counts for the base score are exact for all
words: those above one in 2^21 tokens (at most 2^21 of them) are broadcast, all others are joined.

Defined cases: null text is empty (only its end is scored); blank texts have no words; rows without doc_id train and
are not held out; repeated rows are scored each; without training rows every decision has probability 1/2.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.llm.shared import materialise, read_table
from boundpath.llm.textkernel import Words, segment_sum, words

DEPTH = 5
CHUNK = 250_000  # bytes of text at a time: a worker holds some twenty numbers for each
TOP = 3  # contexts shorter than this are held by the driver
PART = 1 << 17  # byte strings of a task
ENTRIES = 1 << 18  # prices that are broadcast; it decides how many are joined, not what they are
RARE_SHARE = 2.0**-21
END_TOKEN = np.uint64(0x0DDC0FFEE0DDF00D)
_COUNT_SCHEMA = "kind int, item bigint, n bigint"
_SCORE_SCHEMA = (
    "rid bigint, doc_id bigint, n_bytes bigint, n_tokens bigint, known bigint, logs double, score double, "
    "rare array<bigint>, rare_n array<int>, far array<bigint>, far_n array<int>"
)


def strings(w: Words, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """The byte string of each scored place (its context, oldest byte first, then the byte), and places per document."""
    length = np.diff(w.doc_start)
    n_docs, n = w.n_docs, len(w.data)
    stream = np.full(n + n_docs * (depth + 1), 255, np.uint8)
    doc = np.repeat(np.arange(n_docs), length)
    stream[np.arange(n) + doc * (depth + 1) + depth] = w.data
    places = length + 1
    owner = np.repeat(np.arange(n_docs), places)
    at = np.arange(len(owner)) + owner * depth + depth
    key = np.zeros(len(stream), np.uint64)
    for back in range(depth, -1, -1):
        key <<= np.uint64(8)
        key[depth:] |= stream[depth - back : len(stream) - back].astype(np.uint64)
    return key[at], places


class _Tally:
    """Running counts of 64-bit items with bounded memory."""

    def __init__(self, limit: int = 500_000):
        self.parts, self.size, self.limit = [], 0, limit

    def add(self, items: np.ndarray) -> None:
        if not len(items):  # a chunk may have no text held out, or none to learn from
            return
        distinct, n = np.unique(items, return_counts=True)
        self.parts.append((distinct, n))
        self.size += len(distinct)

    def compact(self) -> None:
        if len(self.parts) > 1:
            items = np.concatenate([p[0] for p in self.parts])
            n = np.concatenate([p[1] for p in self.parts])
            order = np.argsort(items, kind="stable")
            items, n = items[order], n[order]
            first = np.flatnonzero(np.concatenate([[True], items[1:] != items[:-1]]))
            self.parts = [(items[first], np.add.reduceat(n, first))]
            self.size = len(first)

    def flush(self, kind: int):
        self.compact()
        for items, n in self.parts:
            for lo in range(0, len(items), 100_000):
                part, m = items[lo : lo + 100_000], n[lo : lo + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), kind, np.int32)), pa.array(part.view(np.int64)), pa.array(m.astype(np.int64))], names=["kind", "item", "n"])
        self.parts, self.size = [], 0


def _count(depth: int):
    """Kind 0: byte strings of training texts; 1: their words; 2: byte strings of texts held out."""

    def run(batches):
        tallies = [_Tally(), _Tally(), _Tally()]
        for batch in batches:
            trains = batch.column(1).to_numpy(zero_copy_only=False).astype(bool)
            for w in words(batch.column(0), "space", CHUNK):
                train = trains[w.first : w.first + w.n_docs]
                keys, places = strings(w, depth)
                learnt = np.repeat(train, places)
                tallies[0].add(keys[learnt])
                tallies[1].add(np.concatenate([w.hash[train[w.doc]], np.full(int(train.sum()), END_TOKEN)]))
                tallies[2].add(keys[~learnt])
                for kind, tally in enumerate(tallies):
                    if tally.size > tally.limit:
                        tally.compact()
                        if tally.size > tally.limit // 2:
                            yield from tally.flush(kind)
        for kind, tally in enumerate(tallies):
            yield from tally.flush(kind)

    return run


def log_gamma(x: np.ndarray) -> np.ndarray:
    """ln of the gamma function for x >= 1/2: Stirling's series after raising the argument by 8."""
    x = np.asarray(x, float)
    low = np.zeros_like(x)
    for i in range(8):
        low += np.log(x + i)
    y = x + 8
    return (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - low


def log_kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """ln of the Krichevsky-Trofimov probability of a sequence with these counts."""
    return log_gamma(zeros + 0.5) + log_gamma(ones + 0.5) - log_gamma(zeros + ones + 1.0) - np.log(np.pi)


class Table:
    """Numbers by 64-bit key: an open-addressing hash table whose lookups are vectorised."""

    _ODD = np.uint64(0x9E3779B97F4A7C15)
    _EMPTY = np.uint64(0xFFFFFFFFFFFFFFFF)

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        bits = max(4, int(2 * len(keys)).bit_length())
        self.bits, self.keys, self.values = bits, np.full(1 << bits, self._EMPTY), np.zeros(1 << bits, values.dtype)
        left, slot = np.arange(len(keys)), self._slot(keys)
        while len(left):
            free = self.keys[slot] == self._EMPTY
            place, who = np.unique(slot[free], return_index=True)
            taken = left[free][who]
            self.keys[place], self.values[place] = keys[taken], values[taken]
            stay = self.keys[slot] != keys[left]
            left, slot = left[stay], (slot[stay] + 1) & ((1 << bits) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * self._ODD) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(values, found)."""
        slot = self._slot(keys)
        found = self.keys[slot] == keys
        value = self.values[slot]
        left = np.flatnonzero(~found & (self.keys[slot] != self._EMPTY))
        slot = slot[left]
        while len(left):
            slot = (slot + 1) & ((1 << self.bits) - 1)
            here = self.keys[slot]
            good = here == keys[left]
            found[left[good]] = True
            value[left[good]] = self.values[slot[good]]
            go = ~good & (here != self._EMPTY)
            left, slot = left[go], slot[go]
        return value, found


def shorter(keys: np.ndarray, n: np.ndarray, first: int, depth: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Strings of first + 1 to depth + 1 bytes and their counts, from longer ones."""
    out = []
    for d in range(first, depth + 1):
        distinct, back = np.unique(keys & np.uint64((1 << (8 * (d + 1))) - 1), return_inverse=True)
        out.append((distinct, np.bincount(back, n, minlength=len(distinct))))
    return out


class ContextTree:
    """Predictions of a weighted context tree, from the counts of byte strings of each length.

    levels[i]: (strings of first + i + 1 bytes, counts), first being the levels of ``above``, the tree of the shorter contexts.
    below: (nodes of the last level, ln of the product of their children's weighted probabilities) if others hold those.
    Without ``above`` a part of a tree has no predictions, only ``weighted``: those of its own first level."""

    def __init__(self, levels: list[tuple[np.ndarray, np.ndarray]], above: ContextTree | None = None, below=None, first: int = 0):
        first = above.depth + 1 if above else first
        self.depth = first + len(levels) - 1
        stop, kt, nodes = [], [], []
        weighted = None  # of the level below, ln
        for d in range(self.depth, first - 1, -1):  # from the leaves up
            keys, zeros, ones = self._bit_nodes(np.asarray(levels[d - first][0], np.uint64), np.asarray(levels[d - first][1], float))
            own = log_kt(zeros, ones)
            if nodes:
                children = np.bincount(self._parents(keys, nodes[0], d + 1), weighted, minlength=len(keys))
            elif below is not None:
                children = np.bincount(np.searchsorted(keys, below[0]), below[1], minlength=len(keys))
            else:
                children = None
            weighted = own if children is None else np.logaddexp(own, children) - np.log(2)
            stop.insert(0, np.ones(len(keys)) if children is None else np.exp(own - np.log(2) - weighted))
            kt.insert(0, (ones + 0.5) / (zeros + ones + 1.0))
            nodes.insert(0, keys)
        self.weighted = (nodes[0], weighted) if nodes else (np.zeros(0, np.uint64), np.zeros(0))
        if first and not above:
            return
        # from the root down: what is settled before a node, and the weight that reaches it
        self.nodes, self.ones = (list(above.nodes), list(above.ones)) if above else ([], [])
        self.passed = above.passed if above else None
        for d, keys in enumerate(nodes, first):
            if self.passed is None:
                settled, reach = np.zeros(len(keys)), np.ones(len(keys))
            else:
                up = self._parents(self.nodes[d - 1], keys, d)
                settled, reach = self.passed[0][up], self.passed[1][up]
            here, last = kt[d - first], stop[d - first]
            self.nodes.append(keys)
            self.ones.append(settled + reach * here)
            self.passed = settled + reach * last * here, reach * (1.0 - last)

    @staticmethod
    def _parents(keys: np.ndarray, deep: np.ndarray, d: int) -> np.ndarray:
        """Where the nodes ``deep`` of level d have their parents in ``keys``: the oldest byte falls away."""
        return np.searchsorted(keys, deep & np.uint64((1 << (8 * d)) - 1)).astype(np.int32)

    @staticmethod
    def _bit_nodes(keys: np.ndarray, n: np.ndarray):
        """Sorted nodes (context, bit prefix) with their counts of zeros and ones; one bit after the other."""
        context, byte = keys & ~np.uint64(255), (keys & np.uint64(255)).astype(np.int64)
        found = []
        for i in range(8):
            prefix = (1 << i) | (byte >> (8 - i))
            distinct, back = np.unique(context | prefix.astype(np.uint64), return_inverse=True)
            total = np.bincount(back, n, minlength=len(distinct))
            ones = np.bincount(back, n * ((byte >> (7 - i)) & 1), minlength=len(distinct))
            found.append((distinct, total - ones, ones))
        node, zeros, ones = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.argsort(node)
        return node[order], zeros[order], ones[order]

    def log10(self, keys: np.ndarray) -> np.ndarray:
        """log10 of the probability of each string's last byte after its context, decision by decision."""
        byte = (keys & np.uint64(255)).astype(np.int64)
        out = np.zeros(len(keys))
        for i in range(8):
            prefix = ((1 << i) | (byte >> (8 - i))).astype(np.uint64)
            p = np.full(len(keys), 0.5)
            left = np.arange(len(keys))
            for d in range(self.depth, -1, -1):
                nodes = self.nodes[d]
                if not len(nodes) or not len(left):
                    continue
                context = (keys[left] >> np.uint64(8)) & np.uint64((1 << (8 * d)) - 1)
                want = (context << np.uint64(8)) | prefix[left]
                slot = np.minimum(np.searchsorted(nodes, want), len(nodes) - 1)
                hit = nodes[slot] == want
                p[left[hit]] = self.ones[d][slot[hit]]
                left = left[~hit]
            out += np.log10(np.where((byte >> (7 - i)) & 1, p, 1.0 - p))
        return out


def _gather(batches) -> tuple[np.ndarray, np.ndarray]:
    """Strings and training counts of a task."""
    found = list(batches)
    keys = [b.column(0).to_numpy().view(np.uint64) for b in found]
    n = [b.column(1).to_numpy().astype(float) for b in found]
    return (np.concatenate(keys), np.concatenate(n)) if found else (np.zeros(0, np.uint64), np.zeros(0))


def _rise(depth: int):
    """What the subtrees of a task give to the nodes of the level above them."""

    def run(batches):
        keys, n = _gather(batches)
        nodes, weighted = ContextTree(shorter(keys[n > 0], n[n > 0], TOP, depth), first=TOP).weighted
        parent, back = np.unique(nodes & np.uint64((1 << (8 * TOP)) - 1), return_inverse=True)
        total = np.bincount(back, weighted, minlength=len(parent))
        yield pa.RecordBatch.from_arrays([pa.array(parent.view(np.int64)), pa.array(total)], names=["node", "ln"])

    return run


def _price(top, depth: int):
    def run(batches):
        keys, n = _gather(batches)
        tree = ContextTree(shorter(keys[n > 0], n[n > 0], TOP, depth), above=top.value) if depth >= TOP else top.value
        for lo in range(0, len(keys), 100_000):
            part = keys[lo : lo + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part.view(np.int64)), pa.array(tree.log10(part))], names=["item", "price"])

    return run


def _per_doc(item: np.ndarray, doc: np.ndarray, n_docs: int) -> tuple[pa.Array, pa.Array]:
    """The distinct items of each document, and how often it has them."""
    order = np.lexsort((item, doc))
    item, doc = item[order], doc[order]
    new = np.ones(len(item), bool)
    new[1:] = (item[1:] != item[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    times = np.diff(np.append(first, len(item))).astype(np.int32)
    start = pa.array(np.concatenate([[0], np.cumsum(np.bincount(doc[first], minlength=n_docs))]).astype(np.int32))
    return pa.ListArray.from_arrays(start, pa.array(item[first].view(np.int64))), pa.ListArray.from_arrays(start, pa.array(times))


def _score(model, depth: int):
    def run(batches):
        prices, frequent = model.value
        for batch in batches:
            rid, ids = batch.column(0), batch.column(1)
            for w in words(batch.column(2), "space", CHUNK):
                keys, places = strings(w, depth)
                price, near = prices.get(keys)
                score = segment_sum(np.where(near, price, 0.0), places)
                far, far_n = _per_doc(keys[~near], np.repeat(np.arange(w.n_docs), places)[~near], w.n_docs)
                item = np.concatenate([w.hash, np.full(w.n_docs, END_TOKEN)])
                doc = np.concatenate([w.doc, np.arange(w.n_docs)])
                count, found = frequent.get(item)
                known = np.bincount(doc[found], minlength=w.n_docs)
                logs = np.bincount(doc[found], np.log10(count[found] + 1.0), minlength=w.n_docs)
                rare, rare_n = _per_doc(item[~found], doc[~found], w.n_docs)
                yield pa.RecordBatch.from_arrays(
                    [
                        rid.slice(w.first, w.n_docs),
                        ids.slice(w.first, w.n_docs),
                        pa.array(np.diff(w.doc_start)),
                        pa.array(np.bincount(doc, minlength=w.n_docs)),
                        pa.array(known.astype(np.int64)),
                        pa.array(logs),
                        pa.array(score),
                        rare,
                        rare_n,
                        far,
                        far_n,
                    ],
                    names=["rid", "doc_id", "n_bytes", "n_tokens", "known", "logs", "score", "rare", "rare_n", "far", "far_n"],
                )

    return run


def count_corpus(texts: DataFrame, depth: int = DEPTH) -> DataFrame:
    """(kind, item, n, uses): kind 0 byte strings of depth + 1, kind 1 words by hash; n counts training texts, uses all.
    texts: text, and whether it trains."""
    found = texts.mapInArrow(_count(depth), _COUNT_SCHEMA)
    found = found.groupBy(F.col("kind").bitwiseAND(1).alias("kind"), "item")
    return materialise(found.agg(F.sum(F.when(F.col("kind") < 2, F.col("n")).otherwise(0)).alias("n"), F.sum("n").alias("uses")), "counts")


def price_strings(counts: DataFrame, depth: int = DEPTH, part: int = PART) -> DataFrame:
    """(item, price): log10 of the probability of each string's last byte after the others, by the tree of all contexts."""
    spark = counts.sparkSession
    grams = counts.filter("kind = 0").select("item", "n")
    top = min(TOP, depth + 1)
    mask = F.lit((1 << (8 * top)) - 1).cast("bigint")
    short = grams.filter("n > 0").groupBy(F.col("item").bitwiseAND(mask).alias("item")).agg(F.sum("n").alias("n")).toArrow()
    keys, n = short["item"].to_numpy().view(np.uint64), short["n"].to_numpy().astype(float)
    parts = max(1, -(-grams.count() // part))
    grams = grams.repartition(parts, F.shiftright("item", 8).bitwiseAND(mask))
    below = None
    if depth >= TOP:
        sums = grams.mapInArrow(_rise(depth), "node bigint, ln double").groupBy("node").agg(F.sum("ln").alias("ln")).toArrow()
        below = sums["node"].to_numpy().view(np.uint64), sums["ln"].to_numpy()
    tree = spark.sparkContext.broadcast(ContextTree(shorter(keys, n, 0, top - 1), below=below))
    prices = materialise(grams.mapInArrow(_price(tree, depth), "item bigint, price double"), "prices")
    tree.destroy()
    return prices


def least_uses(grams: DataFrame, entries: int) -> int:
    """The least number of uses that at most ``entries`` strings have, from a histogram over eighths of powers of two."""
    bins = grams.groupBy(F.floor(F.log2("uses") * 8).alias("bin")).agg(F.count("*"), F.min("uses")).collect()
    kept, least = 0, 1 << 62
    for _, n, low in sorted((tuple(r) for r in bins), reverse=True):
        kept += n
        if kept > entries:
            break
        least = low
    return least


def score_texts(docs: DataFrame, held_out, depth: int = DEPTH, entries: int = ENTRIES, rare_share: float = RARE_SHARE, part: int = PART) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_bytes, bits_per_byte for every row of
    ``docs`` (doc_id, text); the model learns from rows where ``held_out`` (a condition) isn't true.

    score is the tree's log10 probability of the text (A-Z lower-cased); base_score that of add-one word counts."""
    spark = docs.sparkSession
    text = F.col("text").cast("string")
    held = F.coalesce(held_out, F.lit(False))
    counts = count_corpus(docs.select(text.alias("text"), (~held).alias("train")), depth)
    tokens = counts.filter("kind = 1").select("item", F.col("n").alias("c"))
    prices = price_strings(counts, depth, part)
    total, distinct = tokens.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    least = max(1.0, total * rare_share)
    found = tokens.filter(F.col("c") >= least).toArrow()
    frequent = Table(found["item"].to_numpy().view(np.uint64), found["c"].to_numpy().astype(float))
    grams = counts.filter("kind = 0").select("item", "uses")
    often = least_uses(grams, entries)
    near = prices.join(grams.filter(F.col("uses") >= often), "item", "left_semi").toArrow()
    model = spark.sparkContext.broadcast((Table(near["item"].to_numpy().view(np.uint64), near["price"].to_numpy()), frequent))
    del near
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text"))
    scored = materialise(rows.mapInArrow(_score(model, depth), _SCORE_SCHEMA), "scored")
    model.destroy()  # the scores lie in the shared folder: nothing needs the model again
    rare = scored.select("rid", F.explode(F.arrays_zip("rare", "rare_n")).alias("r")).select("rid", F.col("r.rare").alias("item"), F.col("r.rare_n").alias("times"))
    joined = rare.join(tokens.filter(F.col("c") < least), "item")
    joined = joined.select("rid", "times", (F.col("times") * F.log10(F.col("c") + 1.0)).alias("logs"), F.lit(0.0).alias("price"))
    far = scored.select("rid", F.explode(F.arrays_zip("far", "far_n")).alias("r")).select("rid", F.col("r.far").alias("item"), F.col("r.far_n").alias("times"))
    priced = far.join(prices, "item").select("rid", F.lit(0).alias("times"), F.lit(0.0).alias("logs"), (F.col("times") * F.col("price")).alias("price"))
    added = joined.unionByName(priced).groupBy("rid").agg(F.sum("times").alias("more"), F.sum("logs").alias("more_logs"), F.sum("price").alias("more_score"))
    out = scored.drop("rare", "rare_n", "far", "far_n").join(added, "rid", "left")
    out = out.withColumn("score", F.col("score") + F.coalesce("more_score", F.lit(0.0)))
    n_known = F.col("known") + F.coalesce("more", F.lit(0))
    base = F.col("logs") + F.coalesce("more_logs", F.lit(0.0)) - F.col("n_tokens") * F.log10(F.lit(float(total + distinct + 1)))
    return out.select(
        "doc_id",
        held.alias("held_out"),
        "n_tokens",
        n_known.cast("bigint").alias("n_known"),
        F.lit(total).cast("bigint").alias("train_tokens"),
        base.alias("base_score"),
        "score",
        "n_bytes",
        (-F.col("score") * float(np.log2(10)) / F.greatest(F.col("n_bytes"), F.lit(1))).alias("bits_per_byte"),
    )


def op2_lm_score(spark, sf_dir: str) -> DataFrame:
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7
    return score_texts(read_table(spark, sf_dir, "documents").select("doc_id", "text"), fold == 2)


QUERIES = {"op2_lm_score": op2_lm_score}
