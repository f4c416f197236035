"""Main text of web pages: a linear-chain conditional random field over DOM leaf blocks.

Each leaf block is main text or not. Features are the tags and the class, id and role
names of its ancestors, and the shape of its text (length, share in links, sentence
marks, place on the page). Weights are fitted by gradient ascent on the penalised
log-likelihood (exact forward-backward) of labelled pages; pages are decoded by Viterbi.

Spark: one Arrow pass, no shuffle; the fitted weights (some hundred numbers) are
broadcast. Pages are independent, so a lost task is run again.

Defined cases: null or empty html gives an empty text; a page without text likewise;
broken markup is read as browsers mostly do (a head left open ends at the first element or text
that no head can hold); repeated pages give a row each; a very long page is read whole, in time linear in its
length; an empty table gives no rows; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from padgrad.llm.dom_blocks import Block, leaf_blocks

ROWS = "page_id long, url string, text string, n_chars long"
_SCHEMA = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])


def path_features(path: tuple) -> list[str]:
    out = {f"in:{tag}" for tag, _ in path} | {f"name:{n}" for _, parts in path for n in parts}
    if path:
        out |= {f"parent:{path[-1][0]}", f"depth:{min(len(path), 8)}"} | {f"own:{n}" for n in path[-1][1]}
    inner = next((t for t, _ in reversed(path) if t in ("article", "main", "aside", "nav", "header", "footer", "section", "form")), "none")
    return [*sorted(out), f"inner:{inner}", f"inner:{inner}:{path[-1][0] if path else None}"]


def text_features(b: Block, k: int, n: int) -> list[str]:
    words = b.text.count(" ") + 1
    share = b.linked / max(1, len(b.text))
    end = b.text[-1]
    return [
        "bias", f"words:{min(words.bit_length(), 7)}", f"links:{0 if not share else 1 if share < 0.6 else 2}",
        f"ends:{'.' if end in '.!?…' else ',' if end in ',;:' else '-'}",
        f"first:{k == 0}", f"last:{k == n - 1}", f"legal:{'©' in b.text or 'opyright' in b.text}",
    ]


class BlockTagger:
    """Weights are for main text against the rest; ``jump[y][z]`` is for label z after label y."""

    def __init__(self):
        self.weights: dict[str, float] = {}
        self.jump = np.zeros((2, 2))
        self._paths: dict[tuple, float] = {}

    def fit(self, pages: list[tuple[str, set[str]]], rounds: int = 150, rate: float = 0.15, penalty: float = 1e-4) -> BlockTagger:
        ids: dict[str, int] = {}
        feats, labels, sizes = [], [], []
        for page, main in pages:
            blocks = leaf_blocks(page)
            if not blocks:
                continue
            sizes.append(len(blocks))
            for k, b in enumerate(blocks):
                names = path_features(b.path) + text_features(b, k, len(blocks))
                feats.append([ids.setdefault(f, len(ids)) for f in names])
                labels.append(b.text in main)
        flat = np.concatenate([np.array(f) for f in feats])
        row = np.repeat(np.arange(len(feats)), [len(f) for f in feats])
        y = np.array(labels, int)
        # pages as rows of a padded matrix
        n, longest = len(sizes), max(sizes)
        at = np.concatenate([np.arange(s) for s in sizes])
        page = np.repeat(np.arange(n), sizes)
        live = np.zeros((n, longest), bool)
        live[page, at] = True
        gold = np.zeros((n, longest), int)
        gold[page, at] = y
        pairs = live[:, 1:]
        seen = np.array([[((gold[:, :-1] == a) & (gold[:, 1:] == b) & pairs).sum() for b in (0, 1)] for a in (0, 1)], float)
        x = np.zeros(len(ids) + 4)
        m, v = np.zeros_like(x), np.zeros_like(x)
        for t in range(1, rounds + 1):
            w, jump = x[:-4], x[-4:].reshape(2, 2)
            score = np.zeros((n, longest, 2))
            score[page, at, 1] = np.bincount(row, w[flat], len(feats))
            fwd, bwd = np.zeros_like(score), np.zeros_like(score)
            fwd[:, 0] = score[:, 0]
            for k in range(1, longest):
                step = np.logaddexp(fwd[:, k - 1, 0, None] + jump[0], fwd[:, k - 1, 1, None] + jump[1]) + score[:, k]
                fwd[:, k] = np.where(live[:, k, None], step, fwd[:, k - 1])
            for k in range(longest - 2, -1, -1):
                after = score[:, k + 1] + bwd[:, k + 1]
                step = np.stack([np.logaddexp(after[:, 0] + jump[a, 0], after[:, 1] + jump[a, 1]) for a in (0, 1)], 1)
                bwd[:, k] = np.where(live[:, k + 1, None], step, bwd[:, k + 1] * 0)
            total = np.logaddexp(fwd[:, -1, 0], fwd[:, -1, 1])
            p1 = np.exp(fwd[:, :, 1] + bwd[:, :, 1] - total[:, None])[page, at]
            grad = np.zeros_like(x)
            grad[:-4] = np.bincount(flat, (y - p1)[row], len(ids))
            for a in (0, 1):
                for b in (0, 1):
                    lp = fwd[:, :-1, a] + jump[a, b] + score[:, 1:, b] + bwd[:, 1:, b] - total[:, None]
                    grad[len(ids) + 2 * a + b] = seen[a, b] - np.exp(lp)[pairs].sum()
            grad = grad / len(feats) - penalty * x
            m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
            x = x + rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
        self.weights = {f: float(x[k]) for f, k in ids.items()}
        self.jump = x[-4:].reshape(2, 2)
        return self

    def _score(self, b: Block, k: int, n: int) -> float:
        s = self._paths.get(b.path)
        if s is None:
            if len(self._paths) > 50_000:
                self._paths.clear()
            s = self._paths[b.path] = sum(self.weights.get(f, 0.0) for f in path_features(b.path))
        get = self.weights.get
        return s + sum([get(f, 0.0) for f in text_features(b, k, n)])

    def main_blocks(self, page: str | None) -> list[str]:
        """Texts of the blocks on the best label path that are main text."""
        blocks = leaf_blocks(page)
        n = len(blocks)
        (j00, j01), (j10, j11) = self.jump.tolist()
        off, on, back = 0.0, 0.0, []
        for k, b in enumerate(blocks):
            s = self._score(b, k, n)
            if k:
                a, c = off + j00 >= on + j10, off + j01 >= on + j11
                back.append((not a, not c))
                off, on = (off + j00 if a else on + j10), (off + j01 if c else on + j11) + s
            else:
                on = s
        label, out = on > off, []
        for k in range(n - 1, -1, -1):
            if label:
                out.append(blocks[k].text)
            if k:
                label = back[k - 1][label]
        return out[::-1]


def extract_main_text(pages: DataFrame, tagger: BlockTagger | None = None, step: int = 500) -> DataFrame:
    """``(page_id, url, text, n_chars)`` of every page of ``pages`` (``page_id``, ``url``, ``html``)."""
    from padgrad.llm.labelled_pages import labelled_pages

    model = pages.sparkSession.sparkContext.broadcast(tagger or BlockTagger().fit(labelled_pages()))

    def extract(batches):
        for b in batches:
            for at in range(0, b.num_rows, step):
                part = b.slice(at, step)
                texts = [" ".join(model.value.main_blocks(h)) for h in part.column("html").to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column("page_id").cast(pa.int64()), part.column("url").cast(pa.string()), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], schema=_SCHEMA)

    return pages.select("page_id", "url", "html").mapInArrow(extract, ROWS)
