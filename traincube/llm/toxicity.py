"""Toxicity by multiple-instance learning.

A document is a bag of sentences and only the bag has a label. A sentence's
probability is logistic in the words and word beginnings it holds; a document's is
their noisy-or with a leak for bags without evidence. Training the whole on
document labels teaches which sentences offend, so that they can be found.

The model is fitted on at most ``sample`` labelled texts of each label, chosen by a
hash of the id, whole however long they are. Tasks count in how many texts of each
label a feature stands; of the few features that speak for toxic texts, tasks send
which sentence holds which. Only these sparse rows reach the driver, which fits the
weights. Only the features that are kept travel to the tasks; every text is scored whole.

Null and empty texts have no sentences and score the leak. Without labels of both
kinds, or without a feature, the score is the share of toxic labels (0 without any),
and reject() keeps every row. Labels without a document teach nothing but that share.
Rows with null ids are scored but never trained on. Rows that repeat an id count each.
Empty tables give an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.llm.scratch import materialize
from traincube.llm.words import Block, Words, blocks, documents

#: Bytes of a word's beginning that are features, beside the whole word.
BEGINNINGS = (4, 5, 6, 7, 8)

_ENDS = np.zeros(256, bool)
_ENDS[[ord(c) for c in ".!?\n"]] = True
_LETTER = np.zeros(256, bool)
_LETTER[128:] = True
_LOWER = np.arange(256, dtype=np.uint8)
for _c in range(ord("A"), ord("Z") + 1):
    _LOWER[_c] += 32
    _LETTER[[_c, _c + 32]] = True


class Sentences:
    """Features of a block by sentence: ``feature`` hashes, ``sentence`` of each, and text of each sentence."""

    def __init__(self, block: Block):
        data, edge = block.data, block.edge
        plain = _LOWER[data]
        if len(plain):  # capital letters of the Latin-1 range, two bytes in UTF-8
            wide = np.flatnonzero((plain[:-1] == 0xC3) & (plain[1:] >= 0x80) & (plain[1:] <= 0x9E) & (plain[1:] != 0x97)) + 1
            plain[wide] += 32
        words = Words(Block(block.rows, np.where(_LETTER[data], plain, np.uint8(32)), edge), hashed=False)
        cut = np.zeros(len(data) + 1, np.int64)
        cut[1:] = _ENDS[data]
        cut[edge[:-1]] = 1
        self.begin = np.flatnonzero(cut[:-1]) if len(data) else np.zeros(0, np.int64)
        number = np.cumsum(cut) - 1
        self.text = np.searchsorted(edge, self.begin, "right") - 1
        of_word = number[words.begin] if len(words.begin) else np.zeros(0, np.int64)
        size = words.end - words.begin
        feature, sentence = [words.spans(words.begin, words.end)], [of_word]
        for k in BEGINNINGS:
            at = np.flatnonzero(size > k)
            # The salt keeps a beginning apart from the whole word that it spells.
            feature.append(words.spans(words.begin[at], words.begin[at] + k) ^ np.uint64(k))
            sentence.append(of_word[at])
        self.feature, self.sentence = np.concatenate(feature), np.concatenate(sentence)


@dataclass
class Model:
    features: np.ndarray
    weights: np.ndarray
    bias: float
    leak: float

    def sentence_scores(self, s: Sentences) -> np.ndarray:
        """Probability of each sentence; 0 without a known feature."""
        if not len(self.features):
            return np.zeros(len(s.begin))
        at = np.minimum(np.searchsorted(self.features, s.feature), len(self.features) - 1)
        hit = np.flatnonzero(self.features[at] == s.feature)
        total = np.bincount(s.sentence[hit], weights=self.weights[at[hit]], minlength=len(s.begin))
        some = np.bincount(s.sentence[hit], minlength=len(s.begin)) > 0
        return np.where(some, 1 / (1 + np.exp(-(total + self.bias))), 0.0)

    def noisy_or(self, p: np.ndarray, text: np.ndarray, n: int) -> np.ndarray:
        clean = np.bincount(text, weights=np.log1p(-np.minimum(p, 1 - 1e-12)), minlength=n)
        return 1 - (1 - self.leak) * np.exp(clean)


def _label_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """In how many texts of each label every feature stands, summed as far as memory holds them."""
    held: list[tuple] = []
    rows = 0

    def emit() -> pa.RecordBatch:
        f, pos, neg = (np.concatenate(x) for x in zip(*held))
        own, back = np.unique(f, return_inverse=True)
        return pa.RecordBatch.from_arrays([pa.array(own.astype(np.int64)), *(pa.array(np.bincount(back, weights=x, minlength=len(own)).astype(np.int64)) for x in (pos, neg))], ["feature", "pos", "neg"])

    for block in blocks(batches):
        s, label = Sentences(block), block.column("label").astype(np.int64)
        text = s.text[s.sentence]
        order = np.lexsort((text, s.feature))
        f, d = s.feature[order], text[order]
        new = np.ones(len(f), bool)
        new[1:] = (f[1:] != f[:-1]) | (d[1:] != d[:-1])
        held.append((f[new], label[d[new]], 1 - label[d[new]]))
        rows += int(new.sum())
        if rows > 500_000:
            yield emit()
            held, rows = [], 0
    if held:
        yield emit()


def fit(sentence: np.ndarray, slot: np.ndarray, text: np.ndarray, label: np.ndarray, weight: np.ndarray, n_features: int, rounds: int = 300) -> tuple[np.ndarray, float, float]:
    """Weights, bias and leak of the noisy-or of logistic sentences, by gradient steps on the documents' likelihood.

    Sentence ``sentence[i]`` holds feature ``slot[i]``; text: that of each sentence;
    label and weight: of each text, its label and what it counts.
    """
    x = np.concatenate((np.full(n_features, 0.5), [-1.0, -4.0]))
    m, v = np.zeros_like(x), np.zeros_like(x)
    for t in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-(np.bincount(sentence, weights=x[slot], minlength=len(text)) + x[-2])))
        leak = 1 / (1 + np.exp(-x[-1]))
        clean = np.bincount(text, weights=np.log1p(-np.minimum(p, 1 - 1e-12)), minlength=len(label)) + np.log1p(-leak)
        bag = np.clip(-np.expm1(clean), 1e-9, None)
        pull = weight * np.where(label > 0, (1 - bag).clip(0) / bag, -1.0)
        up = pull[text] * p
        grad = np.concatenate((np.bincount(slot, weights=up[sentence], minlength=n_features), [up.sum(), (pull * leak).sum()])) / weight.sum()
        grad[:-2] -= 2e-4 * x[:-2]
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        x += 0.05 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return x[:-2], float(x[-2]), float(1 / (1 + np.exp(-x[-1])))


def _hits(kept: np.ndarray):
    """Of each text, by row of the sample: its label and, packed, which of its sentences holds which kept feature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches):
            s = Sentences(block)
            slot = np.minimum(np.searchsorted(kept, s.feature), len(kept) - 1)
            hit = np.flatnonzero(kept[slot] == s.feature)
            slot, sentence = slot[hit].astype(np.int32), s.sentence[hit]
            of = s.text[sentence]
            order = np.argsort(of, kind="stable")
            cuts = np.searchsorted(of[order], np.arange(len(block) + 1)).tolist()
            packed = [[x[order[a:b]].astype(np.int32).tobytes() for a, b in zip(cuts, cuts[1:])] for x in (sentence, slot)]
            yield pa.RecordBatch.from_arrays([block.rows.column("id"), block.rows.column("label"), *(pa.array(x, pa.binary()) for x in packed)], ["id", "label", "sentences", "slots"])

    return run


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = 1500, least: float = 22.0) -> Model:
    """Fit on a bounded sample; labels: id_col and label_col, 0 or 1, only of rows to learn from.

    ``least``: likelihood ratio statistic that a feature must reach to be kept.
    """
    known = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("label")).where("id is not null and label in (0, 1)")
    total = {r["label"]: r["n"] for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}
    none = Model(np.zeros(0, np.uint64), np.zeros(0), 0.0, total.get(1, 0) / max(1, sum(total.values())))
    pick = None
    for label in (0, 1):
        own = known.where(F.col("label") == label).orderBy(F.xxhash64("id"), "id").limit(sample)
        pick = own if pick is None else pick.union(own)
    # At most 2 * sample rows of two numbers.
    texts = materialize(documents(docs, text_col, id=F.col(id_col).cast("long")).join(F.broadcast(pick), "id"))
    seen = np.zeros(2, np.int64)
    for r in texts.groupBy("label").agg(F.count("*").alias("n")).collect():
        seen[r["label"]] = r["n"]
    if not seen.all():
        return none
    n, rate = F.col("pos") + F.col("neg"), float(seen[1] / seen.sum())
    part = lambda c, of: F.when(F.col(c) > 0, F.col(c) * F.log(F.col(c) / (n * of))).otherwise(0.0)
    counts = texts.mapInArrow(_label_counts, "feature long, pos long, neg long").groupBy("feature").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    speaks = counts.where((2 * (part("pos", rate) + part("neg", 1 - rate)) >= least) & (F.col("pos") > rate * n))
    kept = np.sort(speaks.select("feature").toArrow().column(0).to_numpy().astype(np.uint64))
    if not len(kept):
        return none
    # A repeated id is a row of its own, so rows are numbered as they come, in an order that the sample fixes.
    got = texts.mapInArrow(_hits(kept), "id long, label int, sentences binary, slots binary").orderBy("id", "label", "sentences", "slots").toArrow()
    label = got.column("label").to_numpy().astype(np.int64)
    sentence, slot = ([np.frombuffer(x, np.int32) for x in got.column(c).to_pylist()] for c in ("sentences", "slots"))
    row = np.repeat(np.arange(len(label)), [len(x) for x in sentence])
    used, at = np.unique(np.stack((row, np.concatenate(sentence))), axis=1, return_inverse=True)
    weight = np.array([total[k] / seen[k] for k in (0, 1)])[label]
    return Model(kept, *fit(at.ravel(), np.concatenate(slot), used[0], label, weight, len(kept)))


_SENTENCES = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, score and ``sentences``, the code-point spans of sentences of probability one half or more."""
    share = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = share.value
        for block in blocks(batches):
            s = Sentences(block)
            p = m.sentence_scores(s)
            chars = np.concatenate(([0], np.cumsum((block.data & 0xC0) != 0x80)))
            end = np.append(s.begin[1:], len(block.data))
            spans: list[list] = [[] for _ in range(len(block))]
            for k in np.flatnonzero(p >= 0.5).tolist():
                d = int(s.text[k])
                first = chars[block.edge[d]]
                spans[d].append({"start": int(chars[s.begin[k]] - first), "end": int(chars[end[k]] - first), "score": float(p[k])})
            yield pa.RecordBatch.from_arrays([block.rows.column("id"), pa.array(m.noisy_or(p, s.text, len(block))), pa.array(spans, _SENTENCES)], ["id", "score", "sentences"])

    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(run, "id long, score double, sentences array<struct<start: long, end: long, score: double>>")


def reject(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """``docs`` without the rows whose text scores ``threshold`` or more; all of them if the model has learned no feature."""
    if not len(model.features):
        return docs
    share = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = share.value
        for block in blocks(batches, column=text_col):
            s = Sentences(block)
            kept = m.noisy_or(m.sentence_scores(s), s.text, len(block)) < threshold
            yield block.rows if kept.all() else block.rows.filter(pa.array(kept))

    return docs.mapInArrow(run, docs.schema)
