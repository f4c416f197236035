"""Text operators do the whole job: no cap on a model, on windows or on rows that share an id."""

import collections
import hashlib
import math

import numpy as np
import pytest
from pyspark.sql import functions as F


@pytest.mark.parametrize("hot", [10**6, 60, 0])
def test_context_tree_is_exact(spark, monkeypatch, hot):
    """Every score against a tree in plain Python with a node for each context, whatever is broadcast."""
    from padgrad.llm import context_tree as ct

    monkeypatch.setattr(ct, "HOT_GRAMS", hot)
    monkeypatch.setattr(ct, "HOT_WORDS", hot // 20)
    rng = np.random.default_rng(5)
    rows = [(k, " ".join("".join(chr(c) for c in rng.integers(97, 102, int(n))) for n in rng.integers(1, 7, 12))) for k in range(12)] + [(None, None), (12, "new ßtext"), (3, "twice"), (3, "twice")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    train = F.coalesce(F.col("doc_id") < 9, F.lit(False))
    scored = ct.score_texts(docs, train).collect()
    got = collections.Counter((r.doc_id, r.n_tokens, round(r.score, 4)) for r in scored)
    words = collections.Counter()
    for i, text in rows:
        if i is not None and i < 9:
            words.update([*(text or "").encode().lower().split(), b""])
    whole = words.total() + len(words) + 1
    base = collections.defaultdict(set)
    for i, text in rows:
        w = [*(text or "").encode().lower().split(), b""]
        base[i].add((sum(words[x] > 0 for x in w), round(sum(math.log10((words[x] + 1) / whole) for x in w), 4)))
    assert all((r.n_known, round(r.base_score, 4)) in base[r.doc_id] for r in scored)

    def coded(text):
        data = bytes([10] * ct.DEPTH) + b" ".join((text or "").encode().lower().split()) + b"\n"
        for at in range(ct.DEPTH, len(data)):
            for t in range(8):
                yield [(data[at - d : at], t, data[at] >> (8 - t)) for d in range(ct.DEPTH + 1)], data[at] >> (7 - t) & 1

    counts, children = collections.defaultdict(lambda: [0, 0]), collections.defaultdict(set)
    for i, text in rows:
        if i is not None and i < 9:
            for path, bit in coded(text):
                for d, node in enumerate(path):
                    counts[node][bit] += 1
                    if d:
                        children[path[d - 1]].add(node)
    blocks = {}

    def block(node):
        if node not in blocks:
            a, b = counts[node]
            stop = math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)
            total = stop if len(node[0]) == ct.DEPTH else np.logaddexp(stop, sum(map(block, children[node]))) - math.log(2)
            blocks[node] = (total, math.exp(stop - math.log(2) - total))
        return blocks[node][0]

    want = collections.Counter()
    for i, text in rows:
        total = 0
        for path, bit in coded(text):
            p = 0
            for node in reversed(path):
                block(node)
                w = 1 if len(node[0]) == ct.DEPTH else blocks[node][1]
                p = w * (counts[node][bit] + 0.5) / (sum(counts[node]) + 1) + (1 - w) * p
            total += math.log10(p)
        want[i, len((text or "").split()) + 1, round(total, 4)] += 1
    flat = lambda c: sorted(c.elements(), key=lambda x: (x[0] is None, x[0] or 0, x[1:]))
    assert [x[:2] for x in flat(got)] == [x[:2] for x in flat(want)]
    assert [x[2] for x in flat(got)] == pytest.approx([x[2] for x in flat(want)], abs=2e-3)


def test_rows_that_share_an_id_are_judged_each(spark):
    from padgrad.llm.decontamination import decontaminate
    from padgrad.llm.near_dedup import drop_near_duplicates

    a, b, c, d = (" ".join(f"{p}{k}" for k in range(40)) for p in "abcd")
    rows = [(1, a), (None, a), (7, a), (7, "clean under seven"), (None, "clean without an id"), (8, b), (8, b), (None, c), (None, c), (None, c + " more"), (9, ""), (9, ""), (None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = collections.Counter(tuple(r) for r in drop_near_duplicates(docs, 80).collect())
    kept_c = [x for x in got if x[1] in (c, c + " more")]
    assert len(kept_c) == 1 and got[kept_c[0]] == 1
    del got[kept_c[0]]
    assert got == collections.Counter([(1, a), (7, "clean under seven"), (None, "clean without an id"), (8, b), (9, ""), (9, ""), (None, None)])
    bench = spark.createDataFrame([(1, d)], "item_id long, text string")
    rows = [(None, f"x {d} y"), (None, "clean without an id"), (7, d), (7, "clean under seven"), (7, "clean under seven"), (None, None)]
    left = decontaminate(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), bench)
    assert collections.Counter(tuple(r) for r in left.collect()) == collections.Counter([rows[1], rows[3], rows[4], rows[5]])


def test_no_window_of_an_edited_passage_is_lost(spark):
    """Against all windows of the item's length, after words were put in, left out or changed."""
    from padgrad.llm.decontamination import find_leaks

    rng = np.random.default_rng(11)
    vocabulary = ["".join(chr(c) for c in rng.integers(97, 123, int(n))) for n in rng.integers(2, 10, 4000)]
    pick = lambda n: [vocabulary[k] for k in rng.integers(0, 4000, n)]
    items = {k: pick(int(rng.integers(30, 60))) for k in range(30)}
    items[30] = [f"r{k % 6}" for k in range(20)] + [f"t{k}" for k in range(12)]  # repeats its own shingles
    items[31] = ["just", "three", "words"]
    rows = []
    for i, words in items.items():
        for _ in range(8):
            w = list(words)
            for _ in range(int(rng.integers(1, 4))):
                p, kind = int(rng.integers(0, 4)), rng.integers(3)
                p = p if rng.random() < 0.5 else max(0, len(w) - 1 - p)
                w[p : p + (kind > 0)] = [] if kind == 1 and len(w) > 1 else pick(1)
            rows.append((len(rows), i, pick(5) + w + pick(int(rng.integers(0, 5)))))

    def weighted(w, k):
        return {x: len(x) for x in (" ".join(w[j : j + k]) for j in range(len(w) - k + 1))}

    want = {}
    for doc, i, w in rows:
        n = len(items[i])
        b = weighted(items[i], min(5, n))
        for start in range(len(w)):
            a = weighted(w[start : start + n], min(5, n))
            s = sum(b[x] for x in a if x in b) / sum({**a, **b}.values())
            if s >= 0.8 and (s, -start) > want.get((doc, i), (0, 0)):
                want[doc, i] = (s, -start)
    docs = spark.createDataFrame([(d, " ".join(w)) for d, _, w in rows], "doc_id long, text string")
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in items.items()], "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.similarity, -r.start) for r in find_leaks(docs, bench).collect()}
    assert len(want) > 60 and got.keys() == want.keys()
    assert all(got[x] == pytest.approx(want[x]) for x in want)


def test_every_name_of_an_element_counts():
    from padgrad.llm.dom_blocks import leaf_blocks

    many = " ".join(f"u{chr(97 + k)}x" for k in range(20))
    (block,) = leaf_blocks(f"<div class='{many} comment'><p>text</p></div>")
    assert "comment" in dict(block.path)["div"]


def test_unclosed_head_and_long_page(spark):
    from padgrad.llm.dom_blocks import leaf_blocks
    from padgrad.llm.main_text import extract_main_text

    texts = lambda page: [b.text for b in leaf_blocks(page)]
    assert texts("<html><head><title>t</title><body><article><p>Hello world.</p></article></body></html>") == ["Hello world."]
    assert texts("<head><meta charset=u><style>p{}</style><article><p>No body tag.</p></article>") == ["No body tag."]
    assert texts("<head><title>t</title> \n plain text<p>after") == ["plain text", "after"]
    assert texts("<head><title>t</title></head><body><template><p>hidden</p></template><p>seen") == ["seen"]
    long = "<html><head><title>t</title><body><article>" + "<p>Some plain words of a long page, with an end.</p>" * 20000 + "</article></body></html>"
    pages = spark.createDataFrame([(1, "u", long, 1), (1, "u", long, 2)], "page_id long, url string, html string, n_chars int")
    rows = extract_main_text(pages).collect()
    assert [r.n_chars for r in rows] == [46 * 20000 - 1] * 2 and extract_main_text(pages.limit(0)).count() == 0


def test_line_repeated_within_few_documents_is_hot(spark):
    """A line that a few documents repeat many times is broadcast, not shuffled as one key."""
    from padgrad.llm import line_dedup

    rows = [(k, "again\n" * 500 + f"own {k}") for k in range(4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    lines = line_dedup._hashed_lines(docs)
    (key,) = line_dedup.frequent_keys(lines, 4).collect()
    assert (key.n, key.held) == (4, 2000) and key.held > 2004 // line_dedup.HOT_SHARE
    got = {r.doc_id: (r.text, r.n_dropped) for r in line_dedup.dedup_lines(docs, 4).collect()}
    assert got == {k: (f"own {k}", 500) for k in range(4)}


def test_viterbi_is_the_best_of_all_label_paths():
    import itertools

    from padgrad.llm.dom_blocks import leaf_blocks
    from padgrad.llm.labelled_pages import labelled_pages
    from padgrad.llm.main_text import BlockTagger

    tagger = BlockTagger().fit(labelled_pages(60), rounds=25)
    seen = 0
    for page, _ in labelled_pages(120, seed=5):
        blocks = leaf_blocks(page)
        if not 2 <= len(blocks) <= 11:
            continue
        seen += 1
        own = [tagger._score(b, k, len(blocks)) for k, b in enumerate(blocks)]

        def value(path):
            return sum(s for s, y in zip(own, path) if y) + sum(tagger.jump[a, b] for a, b in zip(path, path[1:]))

        best = max(itertools.product((0, 1), repeat=len(blocks)), key=value)
        assert tagger.main_blocks(page) == [b.text for b, y in zip(blocks, best) if y]
    assert seen >= 5


def test_quality_votes_are_exact():
    """Scores against a plain loop over all labelled vectors; of equal similarities at the last place any may vote."""
    from padgrad.llm.quality import Neighbours, TermIds, term_weights

    rng = np.random.default_rng(3)
    words = [f"{chr(97 + k % 26)}{chr(97 + k // 26)}" for k in range(60)]
    texts = [" ".join(rng.choice(words, int(rng.integers(3, 30)))) for _ in range(80)]
    model = Neighbours(texts, [float(k % 3 > 0) for k in range(80)], rank=12, neighbours=7, sharpness=3)
    asked = [*texts[:10], *[" ".join(rng.choice(words, 12)) for _ in range(20)], "", None]
    weights = term_weights(asked, TermIds())
    got = model.scores(weights)
    for w, score in zip(weights, got, strict=True):
        v = w.astype(float) @ model.space
        size = np.linalg.norm(v)
        if not size:
            assert score == pytest.approx(model.prior)
            continue
        sims = [(float(v / size @ x), y) for x, y in zip(model.vectors, model.labels, strict=True)]
        near = sorted(sims, reverse=True)[:7]
        votes = [(max(s, 0) ** 3, y) for s, y in near]
        assert score == pytest.approx(sum(a * y for a, y in votes) / sum(a for a, _ in votes), abs=1e-4)


def test_shards_follow_the_fractional_ranks(spark):
    """Against the definition in plain Python: rows by (rank - 1/2) / size of their source, then cut; the seeded order is by bucket and hash."""
    from padgrad.llm.sharding import interleaved_order, shard_rows

    rows = [(k if k % 7 else None, f"text {k % 11}", ["a", "b", None][(k * k) % 3 if k % 2 else 0]) for k in range(97)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    narrow = docs.select("doc_id", "source", F.octet_length("text").cast("long").alias("size"), F.crc32(F.col("text").cast("binary")).cast("long").alias("text_crc32"))
    hashed = narrow.withColumn("h", F.xxhash64(F.lit(17), "doc_id", "text_crc32", "size")).collect()
    order = []
    for s in {r.source for r in hashed}:
        own = sorted((r for r in hashed if r.source == s), key=lambda r: (((r.h % 2**64) >> 16) % 9, r.h, r.doc_id is not None, r.doc_id or 0, r.text_crc32))
        order += [((k + 0.5) / len(own), s is None, s or "", r.h, r.doc_id, r.text_crc32) for k, r in enumerate(own)]
    order.sort(key=lambda x: (x[0], x[1], x[2], x[3], x[4] is not None, x[4] or 0, x[5]))
    placed = interleaved_order(narrow, 97).orderBy("place").collect()
    assert [(r.doc_id, r.source or "", r.text_crc32) for r in placed] == [(x[4], x[2], x[5]) for x in order]
    got = collections.Counter(r.shard for r in shard_rows(docs, 8).collect())
    assert sorted(got.values()) == [12] * 7 + [13]


def test_clashing_names_pass_through(spark):
    from padgrad.llm.decontamination import decontaminate
    from padgrad.llm.near_dedup import drop_near_duplicates

    text = " ".join(f"w{k}" for k in range(30))
    docs = spark.createDataFrame([(1, text, "a", 5), (2, text, "b", 6), (3, "short one", "c", 7)], "doc_id long, text string, __did string, __TH int")
    assert sorted(r.doc_id for r in drop_near_duplicates(docs, 80).collect()) == [1, 3]
    bench = spark.createDataFrame([(1, text)], "item_id long, text string")
    left = decontaminate(docs, bench).collect()
    assert [tuple(r) for r in left] == [(3, "short one", "c", 7)]


def test_pipeline_of_empty_tables(spark, tmp_path):
    import corpus_pipeline

    for name, ddl in (("documents", "doc_id long, text string, lang string, source string, n_chars long"), ("labels", "doc_id long, quality int, toxic int"), ("benchmark", "item_id long, text string")):
        spark.createDataFrame([], ddl).write.parquet(str(tmp_path / f"{name}.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_a_frequent_id_is_spread(spark, monkeypatch):
    """A third of all rows without an id: fingerprints, packing and token files as before, over many tasks."""
    import public_tokenizers

    from padgrad.llm import fingerprint
    from padgrad.llm.packing import pack_documents
    from padgrad.llm.token_files import read_token_files, write_token_files
    from padgrad.shared import fresh_path

    monkeypatch.setattr(fingerprint, "SALTS", 3)
    monkeypatch.setattr(fingerprint, "HOT_IDS", 5)
    rows = [(None if k % 3 == 0 else k, f"Text number {k % 17} has this line.\nAnd this one.") for k in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = fingerprint.fingerprint_edits(docs).collect()
    least = {}
    for i, t in rows:
        key = -1 if i is None else i
        least[key] = min(t, least.get(key, t))
    order = sorted(least, reverse=True)
    for r in got:
        key = -1 if r.doc_id is None else r.doc_id
        after = least[order[(order.index(key) + 1) % len(order)]]
        assert r.edited_sha256 in {hashlib.sha256((t[: len(t) - len(t) // 2] + after[: len(t) // 2]).encode()).hexdigest() for i, t in rows if i == r.doc_id}
    assert collections.Counter(r.doc_id for r in got) == collections.Counter(i for i, _ in rows)
    path = public_tokenizers.path("word_bpe_49k.json")
    folder = fresh_path(spark, "test-ids")
    read = read_token_files(spark, folder, write_token_files(docs, folder, path, 2, False)).orderBy("start").collect()
    assert [r.doc_id is not None for r in read] == [False] * 20 + [True] * 40 and read[-1].start + read[-1].n_tokens == sum(r.n_tokens for r in read)
    packed = pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), 1).groupBy("doc_id").agg(F.sum("length").alias("n")).collect()
    assert len(packed) == 41
