"""Text operators against brute force, on small tables with every awkward case."""

import collections
import hashlib
import math
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

LONG = "long words make a very long text " * 3000
BASE = " ".join(f"w{i}" for i in range(60))
SPECIAL = "a <|endoftext|> b<|startoftext|>"
LEAK = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"
TEXTS = [
    (1, "Shared Line\nown one\nShared line "), (2, "shared line\t\nown two"), (3, None), (4, ""), (5, LONG), (6, BASE), (7, BASE), (8, BASE.upper() + " extra"),
    (9, "one two three"), (10, f"before it {LEAK} after it"), (11, "x\n\n\ny  \n z"), (12, " "), (None, "shared line\nno id"), (13, "Grüße aus É\nshared line"), (14, "tab\tand \x0b feed"), (15, SPECIAL),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "s" if i and i % 3 else None, 7, b"x", "node", 1) for i, t in TEXTS]
    rows.append(rows[5])  # a repeated row
    return spark.createDataFrame(rows, "doc_id long, text string, source string, n_lines long, node binary, key string, drop int").repartition(3)


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def strip(s):
    return s.strip(" \t\n\x0b\x0c\r").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))


def test_line_dedup(docs, none):
    from padgrad.llm.line_dedup import dedup_lines

    got = dedup_lines(docs, 4)
    seen = collections.defaultdict(set)
    for i, t in TEXTS:
        for ln in (t or "").split("\n"):
            seen[strip(ln)].add(i)
    gone = {k for k, v in seen.items() if k and len(v) >= 4}
    assert gone == {"shared line"}
    want = collections.Counter()
    for i, t in [*TEXTS, TEXTS[5]]:
        lines = (t or "").split("\n")
        left = [x for x in lines if strip(x) not in gone]
        want[i, "\n".join(left), len(lines), len(lines) - len(left)] += 1
    assert collections.Counter((r.doc_id, r.text, r.n_lines, r.n_dropped) for r in got.collect()) == want
    assert set(docs.columns) <= set(got.columns) and dedup_lines(none, 4).count() == 0


def test_sharding(docs, none):
    from padgrad.llm.sharding import shard_rows

    rows = shard_rows(docs, 4).collect()
    sizes = collections.Counter(r.shard for r in rows)
    assert len(rows) == 17 and set(sizes.values()) == {4, 5}
    for s in range(4):
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sizes[s]))
    by = collections.Counter((r.source, r.shard) for r in rows)
    for s in {r.source for r in rows}:
        per = [by[s, k] for k in range(4)]
        assert max(per) - min(per) <= 1
    assert {(r.doc_id, r.size, r.text_crc32) for r in rows} == {(i, len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for i, t in TEXTS}
    assert shard_rows(none, 4).count() == 0


def jaccard_components(rows, percent):
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append(frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset())
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        if i is not None:
            least[find(k)] = min(least.get(find(k), i), i)
    return [least.get(find(k)) for k in range(len(rows))], [len(s) for s in sets]


def test_near_dedup(spark, docs, none):
    from padgrad.llm.near_dedup import near_duplicates

    rows = [*TEXTS, TEXTS[5]]
    comp, sizes = jaccard_components(rows, 80)
    want = collections.Counter((i, n, c, i == c) for (i, _), n, c in zip(rows, sizes, comp, strict=True))
    assert collections.Counter(tuple(r) for r in near_duplicates(docs, 80).collect()) == want
    assert near_duplicates(none, 80).count() == 0
    rng = np.random.default_rng(3)
    family = []
    for k in range(120):  # a family around one text, and chains of edits
        w = [f"b{j}" for j in range(80)] if k % 2 or not family else family[-1][1].split()
        for p in rng.integers(0, 80, int(rng.integers(0, 4))):
            w[p] = f"e{rng.integers(10**6)}"
        family.append((k, " ".join(w)))
    comp, _ = jaccard_components(family, 85)
    got = {r.doc_id: r.component_id for r in near_duplicates(spark.createDataFrame(family, "doc_id long, text string"), 85).collect()}
    assert got == {i: c for (i, _), c in zip(family, comp, strict=True)}


def test_decontamination(spark, docs, none):
    from padgrad.llm.decontamination import decontaminate, find_leaks

    bench = spark.createDataFrame([(1, LEAK), (2, "One two, three!"), (3, None), (4, "words that nobody wrote anywhere at all")], "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.start, round(r.similarity, 6)) for r in find_leaks(docs, bench).collect()}
    assert got == {(10, 1): (2, 1.0), (9, 2): (0, 1.0)}
    left = {r.doc_id for r in decontaminate(docs, bench).collect()}
    assert left == {i for i, _ in TEXTS} - {9, 10}
    assert find_leaks(none, bench).count() == 0 and find_leaks(docs, bench.limit(0)).count() == 0
    one_word_off = f"z {LEAK.replace('kappa', 'other')} z {LEAK} "
    near = spark.createDataFrame([(1, one_word_off)], "doc_id long, text string")
    assert [r.item_id for r in find_leaks(near, bench).collect()] == [1]


def test_simhash_blocks_cover_the_radius():
    rng = np.random.default_rng(0)
    radius, bits = 19, 64
    edges = [bits * i // (radius + 1) for i in range(radius + 2)]
    for _ in range(200):
        flips = set(rng.choice(bits, radius, replace=False).tolist())
        assert any(not flips & set(range(a, b)) for a, b in zip(edges[:-1], edges[1:], strict=True))


def test_fingerprints(docs, none):
    from padgrad.llm.fingerprint import fingerprint_edits

    got = fingerprint_edits(docs).collect()
    assert len(got) == 17 and fingerprint_edits(none).count() == 0
    by = {}
    for i, t in TEXTS:
        by.setdefault(-(2**63) if i is None else i, t or "")
    order = sorted(by, reverse=True)
    for r in got:
        k = -(2**63) if r.doc_id is None else r.doc_id
        text, after = by[k], by[order[(order.index(k) + 1) % len(order)]]
        half = len(text) // 2
        edited = text[: len(text) - half] + after[:half]
        assert r.n_chars == len(text) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        assert edited != text or (r.near_edited == 1 and r.fingerprint == r.edited_fingerprint)
    prints = collections.defaultdict(set)
    for r in got:
        prints[by[-(2**63) if r.doc_id is None else r.doc_id]].add(r.fingerprint)
    assert all(len(v) == 1 for v in prints.values())


def test_peeling_and_larger_sketches(spark):
    """Differences of any size between sets of any sizes, from sketches alone; what does not peel is counted to within a few."""
    from padgrad.llm.fingerprint import difference_size, fingerprint_text, likeness_of, whole_sketch

    rng = np.random.default_rng(1)
    rows = []
    for common in (0, 3, 50, 700):
        for n, m in ((0, 0), (1, 0), (5, 5), (30, 2), (60, 60), (400, 400), (3, 900)):
            shared = rng.integers(-(2**62), 2**62, common).tolist()
            rows.append((shared + rng.integers(-(2**62), 2**62, n).tolist(), shared + rng.integers(-(2**62), 2**62, m).tolist(), n + m, common))
    df = spark.createDataFrame(rows, "a array<long>, b array<long>, want int, common int").withColumn("sa", whole_sketch(F.col("a"))).withColumn("sb", whole_sketch(F.col("b")))
    got = df.select("want", "common", F.size("a").alias("na"), F.size("b").alias("nb"), difference_size(F.col("sa"), F.col("sb")).alias("d"), fingerprint_text(F.col("sa")).alias("fa"), fingerprint_text(F.col("sb")).alias("fb")).collect()
    for r in got:
        assert abs(r.d - r.want) <= 0.02 * r.want, r
        shared = (r.na + r.nb - r.d) / 2
        assert likeness_of(r.fa, r.fb) == pytest.approx(shared / (r.na + r.nb - shared) if r.na + r.nb else 1.0)


def test_fingerprints_of_real_texts_are_jaccard(spark):
    """Likeness against plain sets of paragraphs, and against the two stored strings alone."""
    from padgrad.llm.fingerprint import fingerprint_edits, likeness_of, paragraph_digests

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    rows = sorted(fingerprint_edits(docs).collect(), key=lambda r: -r.doc_id)
    sets = {r.doc_id: set(r.d) for r in docs.select("doc_id", paragraph_digests(F.col("text")).alias("d")).collect()}
    off = 0
    for r, after in zip(rows, [*rows[1:], rows[0]], strict=True):
        a, b = sets[r.doc_id], sets[after.doc_id]
        want = len(a & b) / len(a | b) if a | b else 1.0
        off += abs(r.near_next - want) > 1e-9
        assert abs(r.near_next - want) < 0.02
        assert likeness_of(r.fingerprint, after.fingerprint) == pytest.approx(r.near_next)
        assert likeness_of(r.fingerprint, r.edited_fingerprint) == pytest.approx(r.near_edited)
    assert off <= 0.02 * len(rows)


def test_packing(spark, docs, none):
    import public_tokenizers
    from tokenizers import Tokenizer

    from padgrad.llm.packing import PackCost, pack_documents

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    rows = pack_documents(docs, path, 1, PackCost(window=256), block_tokens=3000).collect()
    want = collections.Counter()
    ids = {}
    for i, t in [*TEXTS, TEXTS[5]]:
        ids[i] = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        want[i] += len(ids[i])
    have = collections.Counter()
    seqs = collections.defaultdict(list)
    for r in rows:
        have[r.doc_id] += r.length
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes())
        seqs[r.sequence_id].append((r.offset, r.length))
    assert have == want and pack_documents(none, path, 1).count() == 0
    for pieces in seqs.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 256


def test_packing_is_optimal():
    from padgrad.llm.packing import PackCost, best_cuts

    cost = PackCost(window=256)
    rng = np.random.default_rng(0)
    for _ in range(20):
        points = np.unique(np.concatenate([[0], np.cumsum(rng.integers(1, 90, 14))]))
        fee = rng.integers(0, 30, len(points))
        fee[[0, -1]] = 0

        def price(borders):
            total = 0
            for a, b in zip(borders[:-1], borders[1:], strict=True):
                n = points[b] - points[a]
                total += (0 if n in cost.unpadded else 256 - n) + fee[b] + cost.per_window
            return total

        best = {0: 0}
        for j in range(1, len(points)):
            best[j] = min(best[i] + price([i, j]) for i in range(j) if points[j] - points[i] <= 256)
        assert price(best_cuts(points, fee, cost)) == best[len(points) - 1]


def test_tokenizer_is_the_library():
    import public_tokenizers
    from tokenizers import Tokenizer

    from padgrad.llm.tokenizing import PieceTokenizer

    hard = ["", None, " a", "a  b", "a   b", "a \n b\n\n\nc", "\n\nx y\n", "tab\there \t z", "it's don't 'll x's", "é̂ mark", "İstanbul ΣΑΣ", "a\0b c", "<|endoftext|> hi", "a <|endoftext|>", "x<|startoftext|><|ENDOFTEXT|> y", "a <| b |> c", "ﬁ ½ Ⅷ", "日本語 テスト", "a\r\nb", "x y", "ǅ ß ẞ", "word!!'s"]
    for name, joins in (("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)):
        path = public_tokenizers.path(name)
        for as_text in (False, True):
            t, library = PieceTokenizer(path, joins, max_pieces=5, specials_as_text=as_text), Tokenizer.from_file(path)
            if as_text:
                library.encode_special_tokens = True
            for _ in range(2):
                ids, n = t.encode(hard)
                at = 0
                for text, k in zip(hard, n, strict=True):
                    assert ids[at : at + k].tolist() == library.encode(text or "", add_special_tokens=False).ids
                    at += k


def test_piece_cache_holds_one_generation():
    """Memory stays that of one full table, words in use stay in it, ids stay the library's."""
    import tracemalloc

    import public_tokenizers
    from padgrad.llm.tokenizing import PieceTokenizer
    from tokenizers import Tokenizer

    path, rng = public_tokenizers.path("byte_bpe_50k.json"), np.random.default_rng(3)
    words = ["".join(chr(97 + c) for c in rng.integers(0, 26, 9)) for _ in range(60_000)]
    runs = [[f"the use of {' '.join(words[at : at + 500])}."] * 2 for at in range(0, len(words), 500)]

    def held(most):
        t = PieceTokenizer(path, True, max_pieces=most)
        tracemalloc.start()
        for k, run in enumerate(runs if most < 10_000 else runs[:20]):
            ids, n = t.encode(run)
            if not k % 20:
                assert ids[: n[0]].tolist() == library.encode(run[0], add_special_tokens=False).ids
        got = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert "use" in t.index and "of" in t.index
        return got

    library = Tokenizer.from_file(path)
    assert held(9_500) < 1.3 * held(10_000)  # the second has 20 runs, 10 000 pieces and no turn


def test_token_files(spark, docs, none):
    import public_tokenizers
    from tokenizers import Tokenizer

    from padgrad.llm.token_files import decode_blocks, encode_blocks, read_token_files, write_token_files
    from padgrad.shared import fresh_path

    rng = np.random.default_rng(0)
    for ids in (np.zeros(0), np.array([7]), np.full(1024, 5), rng.integers(0, 2**32, 5000), np.where(rng.random(4000) < 0.01, 2**32 - 1, rng.integers(0, 50, 4000))):
        blocks = encode_blocks(ids.astype(np.uint32))
        starts = np.cumsum([0, *map(len, blocks)])[:-1].tolist()
        assert np.array_equal(decode_blocks(memoryview(b"".join(blocks)), starts), ids.astype(np.uint32))
    path = public_tokenizers.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    folder = fresh_path(spark, "test-ids")
    rows = read_token_files(spark, folder, write_token_files(docs, folder, path, 2, False)).orderBy("start").collect()
    texts = dict(TEXTS)
    assert [r.doc_id for r in rows] == sorted([i for i, _ in [*TEXTS, TEXTS[5]]], key=lambda i: -1 if i is None else i)
    at = 0
    for r in rows:
        ids = np.array([*tok.encode(texts[r.doc_id] or "", add_special_tokens=False).ids, 2], "<u4")
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    folder = fresh_path(spark, "test-ids")
    assert read_token_files(spark, folder, write_token_files(none, folder, path, 2, False)).count() == 0


def test_quality(spark, docs, none):
    from padgrad.llm.quality import held_out, score_quality

    good = [(100 + k, f"The plain words of line {k} are calm. They end well.", 1) for k in range(40)]
    bad = [(200 + k, "BUY!! NOW!! " * (5 + k), 0) for k in range(40)]
    train = spark.createDataFrame([(i, t) for i, t, _ in good + bad], "doc_id long, text string")
    labels = spark.createDataFrame([(i, q) for i, _, q in good + bad] + [(None, 1), (100, None)], "doc_id long, quality int")
    scored = score_quality(train, labels).withColumn("out", held_out(F.col("doc_id"))).collect()
    assert any(r.out for r in scored) and all((r.quality_score >= 0.3) == (r.doc_id < 200) for r in scored)
    rows = score_quality(docs, labels).collect()
    assert len(rows) == 17 and all(0 <= r.quality_score <= 1 for r in rows)
    assert {r.quality_score for r in score_quality(docs, labels.limit(0)).collect()} == {0.5}
    assert score_quality(none, labels).count() == 0
    assert all(r.out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in scored)


def test_main_text(spark):
    from padgrad.llm.labelled_pages import labelled_pages
    from padgrad.llm.main_text import BlockTagger, extract_main_text

    tagger = BlockTagger().fit(labelled_pages(300))
    wrong = blocks = 0
    from padgrad.llm.dom_blocks import leaf_blocks

    for page, main in labelled_pages(80, seed=77):
        got = collections.Counter(tagger.main_blocks(page))
        want = collections.Counter(b.text for b in leaf_blocks(page) if b.text in main)
        blocks += len(leaf_blocks(page))
        wrong += ((got - want) + (want - got)).total()
    assert wrong / blocks < 0.04
    page = "<html><head><title>t</title><script>var a='</p>';</script></head><body><nav><ul><li><a href='/x'>Home</a></li><li><a href='/y'>News</a></li></ul></nav><div class='ad'>Buy it now.</div><article><h1>The  title</h1><p><b>First part &amp; more<br><p>Second <i>part</i>\n of it is here.</p></article><footer>&copy; me</footer></body></html>"
    rows = [(1, "u", page), (2, None, None), (3, "u", ""), (4, "u", "<p"), (None, "u", "<script>only()</script>"), (5, "u", page[:330])]
    got = {r.page_id: r for r in extract_main_text(spark.createDataFrame(rows, "page_id long, url string, html string"), tagger).collect()}
    assert got[1].text == "The title First part & more Second part of it is here."
    assert all(got[k].text == "" and got[k].n_chars == 0 for k in (2, 3, 4, None)) and got[5].text.startswith("The title")


def test_main_text_on_pages(spark):
    """The given pages hold their main text in one article element."""
    import html
    import re

    from padgrad.llm.main_text import extract_main_text

    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    got = {r.page_id: r.text for r in extract_main_text(pages).collect()}
    for r in pages.collect():
        body = re.search(r"<article>(.*?)(</article>|\Z)", r.html, re.S)[1]
        parts = [" ".join(html.unescape(re.sub(r"</?b>", "", x)).split()) for x in re.split(r"</?(?:h1|p|br)[^>]*>", body)]
        assert got[r.page_id] == " ".join(x for x in parts if x)


def test_context_tree(spark, docs, none):
    from padgrad.llm.context_tree import score_texts

    rows = [*TEXTS, TEXTS[5]]
    train = F.col("doc_id") != 9
    got = score_texts(docs, train).collect()
    count = collections.Counter()
    for i, t in rows:
        if i is not None and i != 9:
            count.update([*(t or "").encode().lower().split(), b""])
    n, v = sum(count.values()), len(count)
    want = {}
    for i, t in rows:
        w = [*(t or "").encode().lower().split(), b""]
        want[i] = (len(w), sum(count[x] > 0 for x in w), sum(math.log10((count[x] + 1) / (n + v + 1)) for x in w))
    assert len(got) == 17
    for r in got:
        a = want[r.doc_id]
        assert (r.n_tokens, r.n_known, r.train_tokens, r.trained) == (a[0], a[1], n, r.doc_id is not None and r.doc_id != 9)
        assert r.base_score == pytest.approx(a[2]) and r.score < 0
    by = {r.doc_id: r for r in got}
    assert by[5].score / (len(LONG) - 1) > -0.1  # much repeated, so cheap
    assert score_texts(none, train).count() == 0
    untrained = score_texts(docs, F.lit(False)).where("doc_id = 4").first()
    assert untrained.score == pytest.approx(8 * math.log10(0.5), rel=1e-3) and untrained.base_score == 0


def test_context_tree_weights_are_exact_without_collisions(spark):
    """Two contexts of one bit: the mixture by hand against the fitted one."""
    from padgrad.llm import context_tree as ct

    texts = ["ab" * 20]
    data, starts = ct.streams(texts)
    code, _ = ct.grams(data, starts)
    keys, n = np.unique(code, return_counts=True)
    rows = spark.createDataFrame([(ct.GRAM, int(k), int(c)) for k, c in zip(keys, n, strict=True)], "kind int, key long, n long")
    tree = ct.fit_tree(rows)

    def kt(a, b):
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    def weighted(d, context):
        sub = [(g, c) for g, c in zip(keys.tolist(), n.tolist(), strict=True) if (g >> 8) & ((1 << 8 * d) - 1) == context]
        zeros, ones = sum(c for g, c in sub if not g & 1), sum(c for g, c in sub if g & 1)
        sub = [(g, c) for g, c in sub]
        stop = kt(zeros, ones)
        if d == ct.DEPTH:
            return stop, 1.0
        below = sum(weighted(d + 1, x)[0] for x in {(g >> 8) & ((1 << 8 * (d + 1)) - 1) for g, _ in sub})
        total = np.logaddexp(math.log(0.5) + stop, math.log(0.5) + below)
        return total, math.exp(math.log(0.5) + stop - total)

    # the last bit of bytes a (0x61), b (0x62 -> prefix 0x31) and others: take the node of prefix 0x30 (a's first seven bits)
    keep = np.array([(g & 255) >> 1 == 0x30 for g in keys.tolist()])
    keys, n = keys[keep], n[keep]
    slot = ct.node_slots(keys[:1], 7)
    assert float(tree[0][0][slot[0][0]]) == pytest.approx(weighted(0, 0)[1], abs=2e-3)


def test_pipeline(spark, tmp_path):
    import corpus_pipeline
    import pyarrow as pa
    import pyarrow.parquet as pq

    calm = "The plain words of this text are calm and they end well in number {0}. " * 3
    rows = [(k, calm.format(f"{k} {k * 7} {k * k}"), "en", "s", 0) for k in range(60)]
    rows += [(100, BASE, "en", "s", 0), (101, BASE, None, None, 0), (102, LEAK, "en", "s", 0), (103, "BUY!! NOW!! " * 20, "en", "s", 0), (104, None, "en", "s", 0), (None, calm, "en", "s", 0)]
    cols = ["doc_id", "text", "lang", "source", "n_chars"]
    kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64()]
    pq.write_table(pa.table({c: pa.array([r[i] for r in rows], k) for i, (c, k) in enumerate(zip(cols, kinds, strict=True))}), tmp_path / "documents.parquet")
    labels = [(k, 1) for k in range(30)] + [(103, 0), (100, 1), (102, 1)]
    pq.write_table(pa.table({"doc_id": [r[0] for r in labels], "quality": pa.array([r[1] for r in labels], pa.int32())}), tmp_path / "labels.parquet")
    pq.write_table(pa.table({"item_id": [1], "text": [LEAK]}), tmp_path / "benchmark.parquet")
    got = {r.doc_id for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert 100 in got and not got & {101, 102} and set(range(30)) & got
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, str(tmp_path)).columns == docs.columns
