"""Quality filtering by weak supervision.

Each rule votes for good (1) or bad (-1) or abstains (0). Expectation
maximisation over the counts of vote patterns, which cover all documents,
estimates how each rule votes on good and on bad documents, without labels. The
posterior probability of good replaces the rule that all checks must pass: one bad
vote may be outweighed, and several weak ones add up.

Null text counts as empty. A text without words fails the base checks; only its
length votes. Rows with
a null or repeated id are scored like any other; an empty table gives an empty
result. Other columns are neither read nor returned.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from traincube.llm.scratch import materialize
from traincube.llm.words import Words, blocks, documents, sums_by

# The symbols that are counted.
SYMBOLS = "#*$%&|<>"
WINDOW = 5

FEATURES = (
    "id long, n_words long, word_chars long, n_symbols long, n_lines long, n_dup_lines long, n_repeat_words long, n_distinct long, n_top long, "
    "n_upper long, n_letters long, n_letter_words long, n_mark_words long, n_function_words long, n_end_lines long"
)
NAMES = [x.split()[0] for x in FEATURES.split(", ")]

# Common function words of English, French, German and Spanish, and marks that end sentences or parts of them.
FUNCTION_WORDS = (
    "the be to of and that have with a in is it for as on at by this "
    "le la les et de des un une est que pour dans qui ne pas sur "
    "der die das und ist nicht ein eine zu den mit von auf "
    "el los las y en es por con para del se no su al"
)
MARKS = ".,;:!?"
ENDS = (b".", b"!", b"?", b'"', "\u3002".encode(), "\u2026".encode(), "\u201d".encode(), "\u00bb".encode())

_IS_SYMBOL = np.zeros(256, bool)
_IS_SYMBOL[[ord(c) for c in SYMBOLS]] = True
_IS_MARK = np.zeros(256, bool)
_IS_MARK[[ord(c) for c in MARKS]] = True
_STARTS = (np.arange(256) & 0xC0) != 0x80
_UPPER = np.zeros(256, bool)
_UPPER[ord("A") : ord("Z") + 1] = True
_LETTER = _UPPER.copy()
_LETTER[ord("a") : ord("z") + 1] = True
# In a word, bytes of other scripts count as letters.
_IN_WORD = _LETTER | (np.arange(256) >= 0x80)


def _function_hashes() -> np.ndarray:
    own = FUNCTION_WORDS.split()
    text = " ".join([*own, *map(str.capitalize, own), *map(str.upper, own)]).encode()
    return np.unique(Words(next(blocks(iter([pa.RecordBatch.from_pydict({"body": [text]})])))).hash)


def repeated(keys: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Whether the same key occurs again with the same owner."""
    order = np.lexsort((keys, owner))
    k, o = keys[order], owner[order]
    same = (k[1:] == k[:-1]) & (o[1:] == o[:-1])
    out = np.zeros(len(keys), bool)
    out[order[1:]] |= same
    out[order[:-1]] |= same
    return out


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    function_words = _function_hashes()
    for block in blocks(batches):
        words = Words(block)
        n, edge, data = words.counts(), block.edge, block.data
        doc_of = np.repeat(np.arange(len(block)), n)
        keys, whole = words.grams(WINDOW)
        at = np.flatnonzero(whole)
        cover = np.zeros(len(words.hash) + 1, np.int32)
        hit = at[repeated(keys[at], doc_of[at])]
        np.add.at(cover, hit, 1)
        np.add.at(cover, hit + WINDOW, -1)
        order = np.lexsort((words.hash, doc_of))
        fresh = np.ones(len(order), bool)
        fresh[1:] = (words.hash[order][1:] != words.hash[order][:-1]) | (doc_of[order][1:] != doc_of[order][:-1])
        first = np.flatnonzero(fresh)
        top = np.zeros(len(block), np.int64)
        np.maximum.at(top, doc_of[order][first], np.diff(np.append(first, len(order))))
        word_bytes = np.zeros(len(data) + 1, np.int8)
        np.add.at(word_bytes, words.begin, 1)
        np.add.at(word_bytes, words.end, -1)
        in_word = np.cumsum(word_bytes[:-1]).astype(bool)
        letters = np.concatenate(([0], np.cumsum(_IN_WORD[data])))
        marked = _IS_MARK[data[words.end - 1]]
        bare = words.spans(words.begin, words.end - (marked & (words.end - words.begin > 1)))
        lines, dup, ends = [], [], []
        for body in block.bodies():
            own = [x for x in body.split(b"\n") if x.split()]
            lines.append(len(own))
            dup.append(len(own) - len(set(own)))
            ends.append(sum(x.rstrip().endswith(ENDS) for x in own))
        rows = [
            n,
            sums_by(edge, (_STARTS[data] & in_word).astype(np.int64)),
            sums_by(edge, _IS_SYMBOL[data].astype(np.int64)),
            np.array(lines),
            np.array(dup),
            sums_by(words.edge, (np.cumsum(cover[:-1]) > 0).astype(np.int64)),
            np.bincount(doc_of[order][fresh], minlength=len(block)),
            top,
            sums_by(edge, _UPPER[data].astype(np.int64)),
            sums_by(edge, _LETTER[data].astype(np.int64)),
            sums_by(words.edge, (letters[words.end] > letters[words.begin]).astype(np.int64)),
            sums_by(words.edge, marked.astype(np.int64)),
            sums_by(words.edge, np.isin(bare, function_words).astype(np.int64)),
            np.array(ends),
        ]
        yield pa.RecordBatch.from_arrays([block.rows.column("id"), *(pa.array(x, pa.int64()) for x in rows)], NAMES)


def features(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of counts for each document; see FEATURES."""
    return documents(docs, text_col, id=F.col(id_col).cast("long")).mapInArrow(_measure, FEATURES)


def _vote(bad: Column, good: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0)


def default_rules() -> dict[str, Column]:
    """Votes as columns over FEATURES; a user may pass others of the same form.

    Each rule sees one side of a text and may be wrong. Between its two thresholds,
    and on texts too short or of another script than it can judge, it abstains.
    """
    by = lambda c, of: F.coalesce(F.try_divide(F.col(c), F.col(of)), F.lit(0.0))
    per_word = lambda c: by(c, "n_words")
    words, mean = F.col("n_words"), per_word("word_chars")
    some, many = words >= 20, words >= 50
    latin = by("n_letters", "word_chars") > 0.5
    dup, ends, upper = by("n_dup_lines", "n_lines"), by("n_end_lines", "n_lines"), by("n_upper", "n_letters")
    return {
        "length": _vote(words < 20, many),
        "word_length": _vote(latin & ((mean < 3) | (mean > 10)), latin & (mean >= 4) & (mean <= 8)),
        "symbols": _vote(per_word("n_symbols") > 0.1, (words > 0) & (per_word("n_symbols") < 0.01)),
        "lines": _vote(dup > 0.3, (F.col("n_lines") >= 5) & (dup < 0.05)),
        "repeats": _vote(per_word("n_repeat_words") > 0.1, many & (per_word("n_repeat_words") < 0.01)),
        "variety": _vote((words > 0) & (per_word("n_distinct") < 0.3), many & (per_word("n_distinct") > 0.5)),
        "one_word": _vote(some & (per_word("n_top") > 0.2), many & (per_word("n_top") < 0.1)),
        "letters": _vote((words > 0) & (per_word("n_letter_words") < 0.8), per_word("n_letter_words") > 0.95),
        "function_words": _vote(some & latin & (per_word("n_function_words") < 0.05), per_word("n_function_words") > 0.15),
        "marks": _vote(some & latin & (per_word("n_mark_words") < 0.03), per_word("n_mark_words") > 0.06),
        "line_ends": _vote((F.col("n_lines") >= 3) & (ends < 0.3), ends > 0.8),
        "capitals": _vote(latin & (upper > 0.4), latin & (upper < 0.15)),
    }


def fit_votes(patterns: np.ndarray, counts: np.ndarray, rounds: int = 50, prior: float = 0.8, strength: float = 4.0) -> tuple[float, np.ndarray]:
    """EM for P(good) and P(vote | class, not abstaining) by rule.

    patterns: one row for each vote pattern, with -1, 0 and 1; counts: documents
    with it. Returns P(good) and an array [class, rule, bad or good vote]. Abstentions
    say nothing, as they follow from a text's length or script. A Dirichlet prior of
    ``strength`` documents says that a vote is right with probability ``prior``; it
    only settles rules that hardly ever vote.
    """
    cast = np.stack([patterns == -1, patterns == 1], 2).astype(float)
    base = np.array([[prior, 1 - prior], [1 - prior, prior]]) * strength
    good = 1 / (1 + np.exp(-patterns.sum(1).astype(float)))
    share, table = 0.5, np.full((2, patterns.shape[1], 2), 0.5)
    for _ in range(rounds):
        weight = np.stack([(1 - good) * counts, good * counts])
        table = np.einsum("cp,prv->crv", weight, cast) + base[:, None, :]
        table /= table.sum(2, keepdims=True)
        share = float((weight[1].sum() + 1) / (counts.sum() + 2))
        good = posterior(patterns, share, table)
    return share, table


def posterior(patterns: np.ndarray, share: float, table: np.ndarray) -> np.ndarray:
    """P(good) of each pattern, by the votes cast."""
    gain = np.log(table[1]) - np.log(table[0])
    odds = np.log(share) - np.log1p(-share) + (patterns == -1) @ gain[:, 0] + (patterns == 1) @ gain[:, 1]
    return 1 / (1 + np.exp(-odds))


def score(measured: DataFrame, rules: dict[str, Column] | None = None) -> DataFrame:
    """``measured`` with the votes' posterior probability in ``quality``.

    The vote patterns that occur, at most 3 to the number of rules, go to the
    driver with their counts; what a vote weighs comes back as one expression.
    """
    rules = rules or default_rules()
    code = F.lit(0)
    for k, vote in enumerate(rules.values()):
        code = code + (F.coalesce(vote, F.lit(0)) + 1) * 3**k
    coded = measured.withColumn("votes", code.cast("int"))
    seen = {r["votes"]: r["n"] for r in coded.groupBy("votes").agg(F.count("*").alias("n")).collect()}
    if not seen:
        return coded.withColumn("quality", F.lit(None).cast("double"))
    codes = np.array(sorted(seen))
    patterns = codes[:, None] // 3 ** np.arange(len(rules)) % 3 - 1
    share, table = fit_votes(patterns, np.array([seen[c] for c in codes.tolist()], float))
    gain = np.log(table[1]) - np.log(table[0])
    odds = F.lit(float(np.log(share) - np.log1p(-share)))
    for k in range(len(rules)):
        own = F.pmod(F.floor(F.col("votes") / 3**k), F.lit(3))
        odds = odds + F.when(own == 0, float(gain[k, 0])).when(own == 2, float(gain[k, 1])).otherwise(0.0)
    return coded.withColumn("quality", 1 / (1 + F.exp(-odds)))


def quality(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """Counts, base verdict, posterior and ``kept`` for each document."""
    measured = materialize(features(docs, id_col, text_col))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    scored = score(measured).withColumn("base_failed", failed)
    return scored.withColumn("kept", ~F.col("base_failed") & (F.coalesce(F.col("quality"), F.lit(0.0)) >= threshold))
