"""Language-model scores by context-tree weighting over bytes.

A text is coded as its words (A-Z lower-cased) joined by one space and closed by a line
feed. A byte is eight binary decisions; each decision has a tree over the up to
``DEPTH`` bytes before it. Every node keeps how often a 0 and a 1 followed and estimates by
Krichevsky-Trofimov; the node's block probability is the even mixture of its own
estimate and the product of its children's. The chance of the next bit is then,
from the root down, ``w * own + (1 - w) * child`` with ``w`` the weight the data gave
to stopping at the node.

Training is a corpus-wide count: one Arrow pass gives, for each task, its distinct
(DEPTH + 1)-byte strings and words with counts; Spark adds them up. Every context has its own
nodes, so the model grows with the corpus and stays a partitioned table. Strings whose
last ``CUT`` context bytes agree go to one task, where all their nodes of depth ``CUT`` and
more are made and mixed (``deep_nodes``); their block probabilities are summed into the nodes
above, of which there are at most 2^24 for any corpus (``fit_tree``). That gives every distinct
string of the corpus, trained or only scored, one exact log-probability.

A text's score is the sum over its strings, and its unigram base the sum over its words. The most
frequent strings and words (at most ``HOT_GRAMS`` and ``HOT_WORDS``) are broadcast; all others are
joined by a shuffle, words on their 64-bit hash. One pass over the texts gives both the
sums over broadcast keys and the rows to be joined.

Defined cases: null or empty text is the end alone; repeated rows are scored each; with
nothing to learn from, every bit has probability one half and the base is 0; a very long text is
scored whole, in one slice of its own; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from padgrad.llm.shingles import mix
from padgrad.llm.textcols import NO_ID, id_key
from padgrad.shared import written

DEPTH = 5
#: Nodes above this depth are shared by tasks.
CUT = 3
#: Words and strings (16 bytes each) whose values are broadcast; no others are lost, they are joined.
HOT_WORDS, HOT_GRAMS = 1_000_000, 2_000_000
END = 10
#: Kinds of counts: strings of texts to learn from, words, strings of other texts.
GRAM, WORD, OTHER = 0, 1, 2
#: Rows of the scoring pass that hold a text's sums over broadcast keys.
SUMS = 3


def streams(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """All coded bytes with ``DEPTH`` ends before each text, and where each text's own bytes start."""
    lead = bytes([END]) * DEPTH
    parts = [lead + b" ".join((t or "").encode("utf-8", "surrogatepass").lower().split()) + bytes([END]) for t in texts]
    sizes = np.array([len(p) for p in parts])
    return np.frombuffer(b"".join(parts), np.uint8), np.cumsum(sizes) - sizes + DEPTH


_SEEDED = np.random.Generator(np.random.Philox(29))
_OF_BYTE, _OF_PLACE = _SEEDED.integers(0, 2**64, 256, np.uint64), _SEEDED.integers(0, 2**64, 64, np.uint64) | np.uint64(1)


def tokens(data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all words and the ends (0) of coded texts, in no order, and the text of each."""
    inside = (data != 32) & (data != END)
    edge = np.diff(inside.astype(np.int8), prepend=0)  # the last byte is an end
    at = np.flatnonzero(edge == 1)
    sizes = np.flatnonzero(edge == -1) - at
    ends = np.arange(len(starts))
    if not len(at):
        return np.zeros(len(starts), np.uint64), ends
    first = np.cumsum(sizes) - sizes
    place = np.arange(int(sizes.sum())) - np.repeat(first, sizes)
    part = _OF_BYTE[data[inside]] * _OF_PLACE[place & 63]
    if (far := np.flatnonzero(place > 63)).size:
        part[far] *= np.power(_OF_PLACE[0], (place[far] >> 6).astype(np.uint64))
    h = mix(np.add.reduceat(part, first) + sizes.astype(np.uint64))
    return np.concatenate([h, np.zeros(len(starts), np.uint64)]), np.concatenate([np.searchsorted(starts, at, "right") - 1, ends])


def grams(data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The (DEPTH + 1)-byte string that ends at each coded byte, and where each text's begin among them."""
    code = np.zeros(len(data) - DEPTH, np.uint64)
    for j in range(DEPTH + 1):
        code = (code << np.uint64(8)) | data[j : len(data) - DEPTH + j]
    own = np.ones(len(data), bool)
    for j in range(1, DEPTH + 1):
        own[starts - j] = False
    at = np.flatnonzero(own)
    return code[at - DEPTH], np.searchsorted(at, starts)


def node_slots(gram: np.ndarray, bit: int) -> list[np.ndarray]:
    """The node of every depth above ``CUT`` that decides bit ``bit`` of each gram's last byte: its context and the bits before."""
    byte = gram & np.uint64(255)
    prefix = np.uint64(1 << bit) | (byte >> np.uint64(8 - bit))
    context = gram >> np.uint64(8)
    return [(((context & np.uint64((1 << (8 * d)) - 1)) << np.uint64(8)) | prefix).astype(np.int64) for d in range(CUT)]


class Tally:
    """Counts of 64-bit keys, merged as they come; gives rows when it holds ``most`` keys."""

    def __init__(self, most: int = 1_500_000):
        self.most, self.parts, self.held = most, [], 0

    def add(self, keys: np.ndarray):
        k, n = np.unique(keys, return_counts=True)
        self.parts.append((k, n.astype(np.int64)))
        self.held += len(k)
        if self.held < self.most:
            return None
        k, n = self.merged()
        if 2 * len(k) < self.most:
            self.parts, self.held = [(k, n)], len(k)
            return None
        self.parts, self.held = [], 0
        return k, n

    def merged(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.parts:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        if len(self.parts) == 1:
            return self.parts[0]
        keys, counts = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        order = np.argsort(keys, kind="stable")  # parts are runs in order already
        keys = keys[order]
        at = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
        return keys[at], np.add.reduceat(counts[order], at)


class Lookup:
    """Values of 64-bit keys, found for whole arrays at once by open addressing."""

    NONE = np.uint64(2**64 - 1)

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        bits = max(4, (len(keys) + len(keys) // 2).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.values = np.full(1 << bits, self.NONE), np.zeros(1 << bits, values.dtype)
        left, at = np.arange(len(keys)), self._first(keys)
        while len(left):
            free = self.keys[at] == self.NONE
            self.keys[at[free]] = keys[left[free]]
            placed = self.keys[at] == keys[left]
            self.values[at[placed]] = values[left[placed]]
            left, at = left[~placed], (at[~placed] + 1) & self.mask

    def _first(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each key is there, and its value or 0."""
        at = self._first(keys)
        there = self.keys[at]
        found, value = there == keys, self.values[at]
        value[~found] = 0.0
        left = np.flatnonzero(~found & (there != self.NONE))
        at = at[left]
        while len(left):
            at = (at + 1) & self.mask
            there = self.keys[at]
            hit = there == keys[left]
            found[left[hit]], value[left[hit]] = True, self.values[at[hit]]
            go = ~hit & (there != self.NONE)
            left, at = left[go], at[go]
        return found, value


def _slices(batches, most_bytes: int = 500_000):
    """Runs of rows of about ``most_bytes`` of text."""
    for b in batches:
        texts = b.column("text").to_pylist()
        at = size = 0
        for k, t in enumerate(texts):
            size += len(t or "")
            if size >= most_bytes or k == len(texts) - 1:
                yield b.slice(at, k + 1 - at), texts[at : k + 1]
                at, size = k + 1, 0


def corpus_counts(docs: DataFrame) -> DataFrame:
    """``(kind, key, n)``: coded byte strings of all texts, and words of ``trained`` ones by hash (the end is word 0)."""

    def count(batches):
        from padgrad.llm.workers import tidy

        tidy("counts")
        tallies = {GRAM: Tally(), WORD: Tally(), OTHER: Tally()}

        def rows(kind, k, n):
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(k), kind, np.int32)), pa.array(k.view(np.int64)), pa.array(n)], names=["kind", "key", "n"])

        for part, texts in _slices(batches):
            learn = part.column("trained").to_pylist()
            new = []
            if other := [t for t, x in zip(texts, learn, strict=True) if not x]:
                new.append((OTHER, grams(*streams(other))[0]))
            if own := [t for t, x in zip(texts, learn, strict=True) if x]:
                data, starts = streams(own)
                new += [(GRAM, grams(data, starts)[0]), (WORD, tokens(data, starts)[0])]
            for kind, keys in new:
                if (full := tallies[kind].add(keys)) is not None:
                    yield rows(kind, *full)
        for kind, t in tallies.items():
            yield rows(kind, *t.merged())

    found = docs.select("text", "trained").mapInArrow(count, "kind int, key long, n long")
    return found.groupBy("kind", "key").agg(F.sum("n").alias("n"))


def _ln_gamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series after six steps of the recurrence; x > 0."""
    y = x + 6
    rise = np.ones_like(x)
    for k in range(6):
        rise = rise * (x + k)
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - np.log(rise)


def block_estimate(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Natural log of the Krichevsky-Trofimov probability of a block."""
    return _ln_gamma(zeros + 0.5) + _ln_gamma(ones + 0.5) - _ln_gamma(zeros + ones + 1.0) - math.log(math.pi)


def _mixed(zeros: np.ndarray, ones: np.ndarray, split: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Log block probability of nodes whose children's sum to ``split``, and the weight of stopping there."""
    stop = math.log(0.5) + block_estimate(zeros, ones)
    block = np.logaddexp(stop, math.log(0.5) + split)
    return block, np.exp(stop - block)


def deep_tree(like: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, list[tuple]]:
    """Nodes of depth ``CUT`` and more over whole groups of strings.

    ``like`` has the strings in order of context, latest byte first, and last byte. Gives
    for every string and bit the chance of that bit from depth ``CUT`` down, and for every
    bit the nodes of depth ``CUT - 1`` above with summed counts and log block probabilities.
    """
    # keys[d]: distinct (context of d bytes, last byte); to[d]: from those of depth d + 1
    keys, counts, to = {DEPTH: like}, {DEPTH: n}, {}
    for d in range(DEPTH - 1, CUT - 2, -1):
        k = keys[d + 1]
        short = ((k >> 16) << 8) | (k & 255)
        keys[d], to[d] = np.unique(short, return_inverse=True)
        counts[d] = np.bincount(to[d], counts[d + 1], len(keys[d])).astype(np.int64)
    chance, above = np.empty((len(like), 8), np.float32), []
    for t in range(8):
        levels, split = {}, None
        for d in range(DEPTH, CUT - 1, -1):
            node = ((keys[d] >> 8) << 8) | (1 << t) | ((keys[d] & 255) >> (8 - t))
            first = np.ones(len(node), bool)
            first[1:] = node[1:] != node[:-1]
            at, run = np.flatnonzero(first), np.cumsum(first) - 1
            bit = (keys[d] >> (7 - t)) & 1
            zeros, ones = np.add.reduceat(counts[d] * (1 - bit), at), np.add.reduceat(counts[d] * bit, at)
            if d == DEPTH:
                block, w = block_estimate(zeros, ones), np.ones(len(at))
            else:
                parent = np.empty(len(levels[d + 1][0]), np.int64)
                parent[levels[d + 1][1]] = run[to[d]]
                block, w = _mixed(zeros, ones, np.bincount(parent, levels[d + 1][4], len(at)))
            levels[d] = (zeros, run, ones, w, block, node[at])
        own = np.arange(len(like))
        for d in range(DEPTH, CUT - 1, -1):
            own = own if d == DEPTH else to[d][own]
            zeros, run, ones, w = levels[d][:4]
            r = run[own]
            hit = np.where((like >> (7 - t)) & 1 == 1, ones[r], zeros[r])
            mine = (hit + 0.5) / (zeros[r] + ones[r] + 1.0)
            p = mine if d == DEPTH else w[r] * mine + (1 - w[r]) * p
        chance[:, t] = p
        zeros, _, ones, _, block, node = levels[CUT]
        up = ((node >> 16) << 8) | (node & 255)
        shared, inverse = np.unique(up, return_inverse=True)
        above.append((shared, *(np.bincount(inverse, v, len(shared)) for v in (zeros, ones, block))))
    return chance, above


_DEEP = pa.schema([("key", pa.int64()), ("held", pa.int64()), ("chance", pa.list_(pa.float32())), ("node", pa.int64()), ("n0", pa.int64()), ("n1", pa.int64()), ("block", pa.float64())])


def _gram_of(like: np.ndarray) -> np.ndarray:
    """The strings of keys in order of context."""
    out = like & 255
    for j in range(1, DEPTH + 1):
        out = out | (((like >> (8 * (DEPTH + 1 - j))) & 255) << (8 * j))
    return out


def _upper_of(node: np.ndarray) -> np.ndarray:
    """The number that ``node_slots`` gives to nodes of depth ``CUT - 1`` whose context is written latest byte first."""
    out = node & 255
    for j in range(1, CUT):
        out = out | (((node >> (8 * (CUT - j))) & 255) << (8 * j))
    return out


def deep_nodes(counts: DataFrame) -> DataFrame:
    """Rows of two kinds: ``key, held, chance`` of each string (``held``: times it occurs at all), and ``node, n0, n1, block`` of parts of the nodes of depth ``CUT - 1``."""

    def expand(batches):
        def nodes(like, n, held):
            k, inverse = np.unique(like, return_inverse=True)
            n, held = (np.bincount(inverse, v, len(k)).astype(np.int64) for v in (n, held))
            chance, above = deep_tree(k, n)
            size = len(k)
            flat = pa.ListArray.from_arrays(pa.array(np.arange(0, 8 * size + 1, 8, dtype=np.int32)), pa.array(chance.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(_gram_of(k)), pa.array(held), flat, *(pa.nulls(size, f.type) for f in list(_DEEP)[3:])], schema=_DEEP)
            for node, n0, n1, block in above:
                size = len(node)
                yield pa.RecordBatch.from_arrays([*(pa.nulls(size, f.type) for f in list(_DEEP)[:3]), pa.array(_upper_of(node)), pa.array(n0.astype(np.int64)), pa.array(n1.astype(np.int64)), pa.array(block)], schema=_DEEP)

        parts, size = [], 0
        for b in batches:
            parts.append([b.column(c).to_numpy() for c in ("like", "n", "held")])
            size += b.num_rows
            if size < 100_000:
                continue
            like, n, held = (np.concatenate(x) for x in zip(*parts, strict=True))
            group = like >> (8 * (DEPTH + 1 - CUT))
            cut = int(np.searchsorted(group, group[-1]))  # the last group may go on
            if cut:
                yield from nodes(like[:cut], n[:cut], held[:cut])
            parts, size = [[like[cut:], n[cut:], held[cut:]]], size - cut
        if size:
            yield from nodes(*(np.concatenate(x) for x in zip(*parts, strict=True)))

    byte = [F.shiftrightunsigned("key", 8 * j).bitwiseAND(F.lit(255)) for j in range(DEPTH + 1)]
    like = byte[0]
    for j in range(1, DEPTH + 1):
        like = like + F.shiftleft(byte[j], 8 * (DEPTH + 1 - j))
    own = F.when(F.col("kind") == GRAM, F.col("n")).otherwise(F.lit(0)).cast("long")
    rows = counts.where(F.col("kind") != WORD).select(like.alias("like"), own.alias("n"), F.col("n").alias("held"))
    rows = rows.repartition(F.shiftrightunsigned("like", 8 * (DEPTH + 1 - CUT))).sortWithinPartitions("like")
    return rows.mapInArrow(expand, "key long, held long, chance array<float>, node long, n0 long, n1 long, block double")


def upper_tree(deep: DataFrame) -> list[tuple[np.ndarray, ...]]:
    """For each depth above ``CUT`` the stopping weights, counts of 0 and 1, and numbers of its nodes; at most 2^24 rows come to the driver."""
    parts = deep.where("node is not null").groupBy("node").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"), F.sum("block").alias("block"))
    rows = parts.toArrow()
    node, n0, n1, split = (rows.column(c).to_numpy() for c in ("node", "n0", "n1", "block"))
    order = np.argsort(node)
    node, n0, n1, split = node[order], n0[order], n1[order], split[order]
    out = []
    for d in range(CUT - 1, -1, -1):
        block, w = _mixed(n0, n1, split)
        out.append((w, n0, n1, node))
        if d:  # the earliest byte of the context goes
            up = (((node >> 8) & ((1 << (8 * (d - 1))) - 1)) << 8) | (node & 255)
            node, inverse = np.unique(up, return_inverse=True)
            n0, n1 = (np.bincount(inverse, v, len(node)).astype(np.int64) for v in (n0, n1))
            split = np.bincount(inverse, block, len(node))
    w, n0, n1, node = out[-1]  # the root's nodes are told by place
    full = [np.full(256, 0.5), np.zeros(256, np.int64), np.zeros(256, np.int64), np.arange(256)]
    for whole, part in zip(full, (w, n0, n1), strict=False):
        whole[node] = part
    out[-1] = tuple(full)
    return out[::-1]


def fit_tree(counts: DataFrame) -> list[tuple[np.ndarray, ...]]:
    """``upper_tree`` of counts."""
    return upper_tree(written(deep_nodes(counts), "tree-deep"))


def gram_log10(tree: list[tuple[np.ndarray, ...]], gram: np.ndarray, chance: np.ndarray) -> np.ndarray:
    """log10 probability of the last byte of each gram; ``chance`` has each bit's from depth ``CUT`` down."""
    total = np.zeros(len(gram))
    for t in range(8):
        slots = node_slots(gram, t)
        one = ((gram >> np.uint64(7 - t)) & np.uint64(1)).astype(bool)
        p = chance[:, t].astype(np.float64)
        for d in range(CUT - 1, -1, -1):
            w, n0, n1, node = tree[d]
            at = np.searchsorted(node, slots[d])
            p += w[at] * ((np.where(one, n1[at], n0[at]) + 0.5) / (n0[at] + n1[at] + 1.0) - p)
        total += np.log10(p)
    return total


def gram_scores(counts: DataFrame) -> DataFrame:
    """``(key, held, score)``: log10 probability of the last byte of each string after the bytes before it."""
    deep = written(deep_nodes(counts), "tree-deep")
    tree = counts.sparkSession.sparkContext.broadcast(upper_tree(deep))

    def score(batches):
        for b in batches:
            gram = b.column("key").to_numpy().view(np.uint64)
            chance = b.column("chance").flatten().to_numpy().reshape(-1, 8)
            yield pa.RecordBatch.from_arrays([b.column("key"), b.column("held"), pa.array(gram_log10(tree.value, gram, chance))], names=["key", "held", "score"])

    return deep.where("key is not null").select("key", "held", "chance").mapInArrow(score, "key long, held long, score double")


def _hot_floor(rows: DataFrame, column: str, most: int) -> int:
    """The least value of ``column`` from which on there are at most ``most`` rows."""
    step = F.floor(F.log2(F.col(column).cast("double")) * 16).cast("int")
    sizes = sorted((r["step"], r["low"], r["c"]) for r in rows.groupBy(step.alias("step")).agg(F.min(column).alias("low"), F.count("*").alias("c")).collect())  # at most 16 * 63 rows
    floor, total = 1 << 62, 0
    for _, low, c in reversed(sizes):
        total += c
        if total > most:
            break
        floor = low
    return floor


_SCORED = pa.schema([("row", pa.int64()), ("kind", pa.int32()), ("key", pa.int64()), ("times", pa.int32()), ("did", pa.int64()), ("trained", pa.bool_()), ("n_tokens", pa.int64()), ("known", pa.int64()), ("base", pa.float64()), ("score", pa.float64())])
_tables: dict[str, tuple[Lookup, Lookup]] = {}


def _counted(key: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct ``(row, key)`` and how often each is there."""
    order = np.lexsort((key, row))
    key, row = key[order], row[order]
    at = np.flatnonzero(np.append(True, (key[1:] != key[:-1]) | (row[1:] != row[:-1]))) if len(key) else np.zeros(0, np.int64)
    return key[at], row[at], np.diff(np.append(at, len(key))).astype(np.int32)


def _scorer(common, likely):
    """Arrow pass giving, as ``_SCORED``, each text's sums over broadcast words and strings, and its other words and strings."""

    model = uuid.uuid4().hex

    def score(batches):
        from padgrad.llm.workers import tidy

        tidy(f"scores {model}")
        if model not in _tables:  # one pair for each worker process
            _tables.clear()
            _tables[model] = Lookup(*common.value), Lookup(*likely.value)
        of_word, of_string = _tables[model]
        for part, texts in _slices(batches):
            size = len(texts)
            data, starts = streams(texts)
            flat, row = tokens(data, starts)
            known, value = of_word.find(flat)
            code, begins = grams(data, starts)
            likely_, score_ = of_string.find(code)
            sums = [part.column("row"), pa.array(np.full(size, SUMS, np.int32)), pa.nulls(size, pa.int64()), pa.nulls(size, pa.int32()), part.column("did"), part.column("trained"), pa.array(np.bincount(row, minlength=size)), pa.array(np.bincount(row[known], minlength=size)), pa.array(np.bincount(row, value, size)), pa.array(np.add.reduceat(score_, begins, dtype=np.float64))]
            yield pa.RecordBatch.from_arrays(sums, schema=_SCORED)
            far = np.flatnonzero(~likely_)
            for kind, key, r in ((WORD, flat[~known], row[~known]), (GRAM, code[far], np.searchsorted(begins, far, "right") - 1)):
                key, r, times = _counted(key, r)
                n = len(key)
                rest = [pa.nulls(n, f.type) for f in list(_SCORED)[4:]]
                yield pa.RecordBatch.from_arrays([part.column("row").take(pa.array(r)), pa.array(np.full(n, kind, np.int32)), pa.array(key.view(np.int64)), pa.array(times), *rest], schema=_SCORED)

    return score


def score_texts(docs: DataFrame, train: Column) -> DataFrame:
    """``(doc_id, trained, n_tokens, n_known, train_tokens, base_score, score)`` of every row; learns from rows where ``train``."""
    spark = docs.sparkSession
    rows = docs.select(id_key(F.col("doc_id")).alias("did"), "text", F.coalesce(train, F.lit(False)).alias("trained"))
    counts = written(corpus_counts(rows), "corpus-counts")
    scores = written(gram_scores(counts), "gram-scores")
    words = counts.where(F.col("kind") == WORD)
    n, v = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    least, floor = _hot_floor(scores, "held", HOT_GRAMS), _hot_floor(words, "n", HOT_WORDS)

    def shared(table, dtype):  # at most HOT_GRAMS or HOT_WORDS rows
        top = table.toArrow()
        return spark.sparkContext.broadcast((top.column("key").to_numpy().view(np.uint64), top.column("value").to_numpy().astype(dtype)))

    words = words.select("kind", "key", "n", F.log10(F.col("n") + 1.0).alias("value"))
    likely = shared(scores.where(F.col("held") >= least).select("key", F.col("score").alias("value")), np.float32)
    common = shared(words.where((F.col("n") >= floor) | (F.col("key") == 0)).select("key", "value"), np.float64)
    repeated = not rows.groupBy("did").count().where("count > 1").isEmpty()
    keyed = rows.withColumn("row", F.xxhash64("did", F.coalesce("text", F.lit(""))) if repeated else F.col("did")).select("row", "did", "text", "trained")
    ddl = "row long, kind int, key long, times int, did long, trained boolean, n_tokens long, known long, base double, score double"
    parts = written(keyed.mapInArrow(_scorer(common, likely), ddl), "text-scores")
    base = parts.where(F.col("kind") == SUMS).select("row", "did", "trained", "n_tokens", "known", "base", "score")
    cold = parts.where(F.col("kind") != SUMS).select("row", "kind", "key", "times")
    values = words.where((F.col("n") < floor) & (F.col("key") != 0)).select("kind", "key", "value")
    values = values.unionByName(scores.where(F.col("held") < least).select(F.lit(GRAM).alias("kind"), "key", F.col("score").alias("value")))
    found = cold.join(values.hint("merge"), ["kind", "key"])
    is_word, part = F.col("kind") == WORD, F.col("times") * F.col("value")
    cold_sums = found.groupBy("row").agg(F.sum(F.when(is_word, F.col("times"))).alias("far_known"), F.sum(F.when(is_word, part)).alias("far_base"), F.sum(F.when(~is_word, part)).alias("far_score"))
    if repeated:
        same = keyed.groupBy("row").agg(F.count("*").alias("copies"))
        cold_sums = cold_sums.join(same, "row").select("row", F.expr("far_known div copies").alias("far_known"), (F.col("far_base") / F.col("copies")).alias("far_base"), (F.col("far_score") / F.col("copies")).alias("far_score"))
    out = base.join(cold_sums, "row", "left")
    return out.select(
        F.when(F.col("did") != NO_ID, F.col("did")).alias("doc_id"), "trained", "n_tokens",
        (F.col("known") + F.coalesce("far_known", F.lit(0))).cast("long").alias("n_known"), F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("far_base", F.lit(0.0)) - F.col("n_tokens") * math.log10(n + v + 1)).alias("base_score"),
        (F.col("score") + F.coalesce("far_score", F.lit(0.0))).alias("score"),
    )
