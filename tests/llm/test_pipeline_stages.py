"""Every stage of the pipeline against plain Python, on what the stage before kept of the smallest tables."""

import collections
import re

import numpy as np
import pytest

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    """Rows after each stage, by its name; each stage reads the last one's rows."""
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = {"start": [tuple(r) for r in docs.collect()]}
    for name, stage in corpus_pipeline.STAGES:
        rows = stage(spark, docs, SF)
        kept = rows.collect()
        out[name] = [tuple(r) for r in kept]
        docs = spark.createDataFrame(kept, rows.schema)
    return out


def test_quality_keeps_what_the_votes_keep(spark, stages):
    import zlib

    from padgrad.llm.quality import Neighbours, TermIds, term_weights

    texts = {r[0]: r[1] or "" for r in stages["start"]}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect() if zlib.crc32(str(r.doc_id).encode()) % 5}
    order = sorted(i for i in labels if i in texts)
    model = Neighbours([texts[i] for i in order], [float(labels[i]) for i in order])
    scores = model.scores(term_weights([r[1] for r in stages["start"]], TermIds()))
    clear = [abs(s - 0.3) > 1e-3 for s in scores]
    got = {r[0] for r in stages["quality"]}
    assert all((r[0] in got) == (s >= 0.3) for r, s, sure in zip(stages["start"], scores, clear, strict=True) if sure)
    assert set(stages["quality"]) <= set(stages["start"]) and len(got) < len(stages["start"])


def test_line_dedup_drops_frequent_lines(stages):
    key = lambda line: line.strip(" \t\n\x0b\x0c\r").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    seen = collections.defaultdict(set)
    for r in stages["quality"]:
        for line in (r[1] or "").split("\n"):
            seen[key(line)].add(r[0])
    gone = {k for k, v in seen.items() if k and len(v) >= 10}
    want = {r[0]: "\n".join(x for x in (r[1] or "").split("\n") if key(x) not in gone) for r in stages["quality"]}
    assert {r[0]: r[1] for r in stages["line_dedup"]} == want
    assert all(r[4] == len(r[1]) for r in stages["line_dedup"])


def test_near_dedup_keeps_one_of_a_group(stages):
    rows = sorted(stages["line_dedup"])
    sets = []
    for r in rows:
        w = (r[1] or "").encode().lower().split()
        sets.append(frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset())
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    want = {rows[k][0] for k in range(len(rows)) if not sets[k] or find(k) == k}
    assert {r[0] for r in stages["near_dedup"]} == want and len(want) < len(rows)


def test_decontamination_drops_whoever_holds_an_item(spark, stages):
    words = lambda t: [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]
    items = [words(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    want = set()
    for r in stages["near_dedup"]:
        w = words(r[1])
        for item in items:
            n, k = len(item), min(5, len(item))
            if not n:
                continue
            shingles = lambda x: {" ".join(x[j : j + k]) for j in range(len(x) - k + 1)}
            b, own = shingles(item), [" ".join(w[j : j + k]) for j in range(len(w) - k + 1)]
            if not any(x in b for x in own):
                continue
            for start in range(len(w)):
                a = set(own[start : max(start, min(len(w), start + n) - k + 1)])
                if a and sum(map(len, a & b)) >= 0.8 * sum(map(len, a | b)):
                    want.add(r[0])
                    break
    got = {r[0] for r in stages["near_dedup"]} - {r[0] for r in stages["decontamination"]}
    assert got == want and want


def test_packing_holds_every_token_once(stages):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = {r[0]: len(tok.encode(r[1] or "", add_special_tokens=False).ids) + 1 for r in stages["decontamination"]}
    have, ends = collections.Counter(), collections.defaultdict(list)
    for doc_id, start, length, _, total, sequence, offset in stages["packing"]:
        have[doc_id] += length
        ends[sequence].append((offset, length))
        assert total == want[doc_id] and start + length <= total
    assert have == want
    for pieces in ends.values():
        offsets, sizes = np.array(sorted(pieces)).T
        assert offsets[0] == 0 and (offsets[1:] == np.cumsum(sizes)[:-1]).all() and sizes.sum() <= 2048


def test_stages_with_python_workers_give_heap_back(monkeypatch):
    import corpus_pipeline

    class Asked(Exception):
        pass

    def ask(spark):
        raise Asked

    monkeypatch.setattr(corpus_pipeline, "shrink_heaps", ask)
    for stage in (corpus_pipeline.quality, corpus_pipeline.near_dedup, corpus_pipeline.packing):
        with pytest.raises(Asked):
            stage(None, None, SF)
