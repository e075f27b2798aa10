"""Quality rules: base counts, and a linear-chain conditional random field over the lines of a text.

The field labels each line that holds a word as content or boilerplate from its own features
and its neighbours' labels. Every text is decoded whole by Viterbi; it is kept if content
lines hold at least ``content_share`` of its words and the base rules don't fail.

Training sees labels of texts alone, so the labels of their lines are latent. A text of label
1 is one whose content lines hold ``content_share`` of its words or more, one of label 0 one
whose content lines hold less. Training begins with a field without steps between lines, fit
as if each line had its text's label. Then each of ``rounds`` rounds gives every line the
label that is more probable under the field, turns the least certain lines of a text round
where that breaks the text's own label, and fits the whole field to the result by gradient
ascent on the likelihood (Adam, exact gradients by the forward-backward sums).

The field is fit on a bounded sample: the ``sample`` labelled ids of smallest hash, with texts
of any length. Executors compute the lines' features; they alone reach the driver. There, a
text of more than ``stretch`` lines is several chains; its label holds for all of them.

Null text is empty and fails the base rules; rows without words, null ids and labels other
than 0 and 1 are left out of training; ids that occur several times count once for each row;
without labels of both kinds every line is content; rows of equal or null ids are judged
apart; an empty table stays empty.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean, small_batches
from forkline.llm.textblock import TextBlock, blocks, mix, windows

# Fixed values of the base rules.
SYMBOLS = b"#*$%&|<>"
REPEAT_WINDOW, LEAST_WORDS, MOST_REPEATED = 8, 20, 30

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(SYMBOLS)] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_STOP = np.zeros(256, bool)
_STOP[list(b".!?\"')")] = True
_FOLLOWS = np.zeros(256, bool)  # bytes inside a multi-byte character
_FOLLOWS[0x80:0xC0] = True

_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_MARK = np.zeros(256, bool)  # ASCII punctuation
_MARK[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True

FEATURES = (
    "bias", "log words", "one or two words", "up to five words", "symbols a word", "bars a word", "ends a sentence", "digits",
    "words equal to the one before", "equals an earlier line", "word length", "capitals", "marks a word", "two marks a word or more",
)


@dataclass(frozen=True)
class Field:
    """State 1 is content. ``unary`` scores content against boilerplate; ``pair[a, b]`` a step from a to b; ``start`` the first line."""

    unary: np.ndarray
    pair: np.ndarray
    start: np.ndarray


@dataclass(frozen=True)
class Settings:
    content_share: float = 0.5
    sample: int = 3000
    rounds: int = 2
    steps: int = 60
    stretch: int = 100
    rate: float = 0.1
    penalty: float = 1e-3


def _within(mask: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(mask, dtype=np.int64)])
    return total[ends] - total[starts]


def _by_doc(h: np.ndarray, doc: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return h + mix(doc.astype(np.uint64), 99)


class Counts:
    """Base counts and line features of one block."""

    def __init__(self, block: TextBlock):
        n = block.n_docs
        s, e, doc = block.words()
        h = block.hashes(s, e)
        self.n_words = np.bincount(doc, minlength=n)
        whole = ~_FOLLOWS[block.data]
        self.word_chars = np.bincount(doc, weights=_within(whole, s, e), minlength=n).astype(np.int64)
        symbol = _SYMBOL[block.data]
        self.n_symbols = _within(symbol, block.edges[:-1], block.edges[1:])

        ls, le, ldoc = block.lines()
        w0, w1 = np.searchsorted(s, ls), np.searchsorted(s, le)
        some = w1 > w0
        ls, le, ldoc, w0, w1 = ls[some], le[some], ldoc[some], w0[some], w1[some]
        key = _by_doc(block.hashes(ls, le), ldoc)
        order = np.argsort(key, kind="stable")
        again = np.zeros(len(key), bool)
        again[order[1:]] = key[order[1:]] == key[order[:-1]]
        self.n_dup_lines = np.bincount(ldoc[again], minlength=n)

        window, inside = windows(h, doc, REPEAT_WINDOW)
        at = np.flatnonzero(inside)
        key = _by_doc(window[at], doc[at])
        order = np.argsort(key)
        ranked = key[order]
        same = ranked[1:] == ranked[:-1]
        twice = at[order[np.concatenate([[False], same]) | np.concatenate([same, [False]])]] if len(at) else at
        cover = np.zeros(len(h) + 1, np.int64)
        np.add.at(cover, twice, 1)
        np.add.at(cover, twice + REPEAT_WINDOW, -1)
        self.n_repeat_words = np.bincount(doc[np.cumsum(cover)[:-1] > 0], minlength=n)

        self.line_doc, self.line_words = ldoc, w1 - w0
        words = np.maximum(w1 - w0, 1)
        echo = np.zeros(len(h), bool)
        echo[1:] = h[1:] == h[:-1]
        # a line's first word has none before it
        echoes = np.concatenate([[0], np.cumsum(echo)])
        last = block.data[np.maximum(e[np.maximum(w1 - 1, 0)] - 1, 0)] if len(ls) else np.zeros(0, np.uint8)
        chars = np.maximum(_within(whole, ls, le), 1)
        marks = _within(_MARK[block.data], ls, le) / words
        self.features = np.stack(
            [
                np.ones(len(ls)),
                np.log1p(w1 - w0) / 3,
                (w1 - w0) <= 2,
                (w1 - w0) <= 5,
                np.minimum(_within(symbol, ls, le) / words, 2),
                np.minimum(_within(block.data == 124, ls, le) / words, 1),
                _STOP[last],
                _within(_DIGIT[block.data], ls, le) / chars,
                (echoes[w1] - echoes[np.minimum(w0 + 1, w1)]) / words,
                again,
                np.minimum(chars / words / 10, 3),
                _within(_UPPER[block.data], ls, le) / chars,
                np.minimum(marks, 3),
                marks >= 2,
            ],
            axis=1,
        ).astype(np.float64)


def _padded(doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """For each position the rows of the texts that reach it: order of texts from long to short, and line index (texts, positions)."""
    count = np.bincount(doc, minlength=n)
    order = np.argsort(-count, kind="stable")
    return order, count


def viterbi(score: np.ndarray, doc: np.ndarray, n: int, field: Field) -> np.ndarray:
    """The most likely state of each line; ties go to content. Steps run over positions, vectorised over texts."""
    order, count = _padded(doc, n)
    first = np.concatenate([[0], np.cumsum(count)])[:-1]
    state = np.zeros(len(score), np.int8)
    if not len(score):
        return state
    longest = int(count.max())
    back = np.zeros((len(score), 2), np.int8)
    best = np.zeros((n, 2))
    for t in range(longest):
        own = order[: int(np.searchsorted(-count[order], -t, side="left"))]
        line = first[own] + t
        if t == 0:
            best[own] = field.start
        else:
            step = best[own][:, :, None] + field.pair[None]
            take = step[:, 1] >= step[:, 0]
            back[line] = take
            best[own] = np.where(take, step[:, 1], step[:, 0])
        best[own, 1] += score[line]
    held = (best[:, 1] >= best[:, 0]).astype(np.int8)
    for t in range(longest - 1, -1, -1):
        own = order[: int(np.searchsorted(-count[order], -t, side="left"))]
        line = first[own] + t
        state[line] = held[own]
        if t:
            held[own] = back[line, held[own]]
    return state


class Lines:
    """Features and words of the lines of ``n`` texts, laid out so that steps run over positions, vectorised over chains.

    A chain is a text, or ``stretch`` lines in a row of a longer one.
    """

    def __init__(self, x: np.ndarray, words: np.ndarray, doc: np.ndarray, n: int, stretch: int = 1 << 40):
        self.x, self.words, self.doc, self.n = x, words, doc, n
        cut = np.ones(len(doc), bool)
        cut[1:] = (doc[1:] != doc[:-1]) | ((np.arange(len(doc)) - np.searchsorted(doc, doc)) % stretch == 0)[1:]
        chain = np.cumsum(cut) - 1
        order, count = _padded(chain, int(cut.sum()))
        self.first = np.cumsum(count) - count
        self.heads = self.first[count > 0]
        self.steps = [order[: int(np.searchsorted(-count[order], -t, side="left"))] for t in range(int(count.max(initial=0)))]
        self.inner = np.ones(len(doc), bool)
        self.inner[self.heads] = False

    def field(self, theta: np.ndarray) -> Field:
        k = self.x.shape[1]
        return Field(theta[:k], theta[k : k + 4].reshape(2, 2), theta[k + 4 :])

    def sums(self, theta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Log sums up to each line, from each line on, over whole texts (told at each line), and scores of content."""
        f = self.field(theta)
        unary = self.x @ f.unary
        forward, backward = np.zeros((len(unary), 2)), np.zeros((len(unary), 2))
        for t, own in enumerate(self.steps):
            line = self.first[own] + t
            a = np.tile(f.start, (len(own), 1)) if t == 0 else np.logaddexp(forward[line - 1, :1] + f.pair[0], forward[line - 1, 1:] + f.pair[1])
            a[:, 1] += unary[line]
            forward[line] = a
        for t in range(len(self.steps) - 2, -1, -1):
            line = self.first[self.steps[t + 1]] + t
            nxt = backward[line + 1].copy()
            nxt[:, 1] += unary[line + 1]
            backward[line] = np.stack([np.logaddexp(f.pair[a, 0] + nxt[:, 0], f.pair[a, 1] + nxt[:, 1]) for a in (0, 1)], axis=1)
        return forward, backward, np.logaddexp(*(forward + backward).T), unary

    def content(self, theta: np.ndarray) -> np.ndarray:
        """Probability of each line to be content."""
        forward, backward, whole, _ = self.sums(theta)
        return np.exp(forward[:, 1] + backward[:, 1] - whole)

    def likelihood(self, theta: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
        """Log likelihood of the labelling ``y`` of all lines, and its gradient."""
        k, f = self.x.shape[1], self.field(theta)
        forward, backward, whole, unary = self.sums(theta)
        at = np.flatnonzero(self.inner)
        truth, expected = np.zeros(k + 6), np.zeros(k + 6)
        truth[:k] = self.x[y == 1].sum(0)
        on = np.exp(forward[:, 1] + backward[:, 1] - whole)
        expected[:k] = on @ self.x
        for a in (0, 1):
            for b in (0, 1):
                truth[k + 2 * a + b] = ((y[at - 1] == a) & (y[at] == b)).sum()
                expected[k + 2 * a + b] = np.exp(forward[at - 1, a] + f.pair[a, b] + backward[at, b] + (unary[at] if b else 0) - whole[at]).sum()
        truth[k + 4 :] = np.bincount(y[self.heads], minlength=2)
        expected[k + 4 :] = [(1 - on[self.heads]).sum(), on[self.heads].sum()]
        return float(truth @ theta - whole[self.heads].sum()), truth - expected


def ascend(lines: Lines, y: np.ndarray, theta: np.ndarray, s: Settings, steps_between: bool) -> np.ndarray:
    """Adam on the penalised likelihood of the labelling; without ``steps_between`` the lines stay independent."""
    k = lines.x.shape[1]
    m, v = np.zeros(k + 6), np.zeros(k + 6)
    for i in range(1, s.steps + 1):
        g = lines.likelihood(theta, y)[1] / lines.n - s.penalty * theta
        if not steps_between:
            g[k:] = 0
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        theta = theta + s.rate * (m / (1 - 0.9**i)) / (np.sqrt(v / (1 - 0.999**i)) + 1e-8)
    return theta


def completed(lines: Lines, on: np.ndarray, y_doc: np.ndarray, share: float) -> np.ndarray:
    """The more probable label of each line, but for the least certain lines of texts whose own label that would break."""
    y = (on >= 0.5).astype(np.int64)
    words = np.bincount(lines.doc, weights=lines.words, minlength=lines.n)
    held = np.bincount(lines.doc, weights=lines.words * y, minlength=lines.n)
    count = np.bincount(lines.doc, minlength=lines.n)
    begin = np.cumsum(count) - count
    for d in np.flatnonzero((count > 0) & ((held >= share * words) != (y_doc == 1))).tolist():
        own = np.arange(begin[d], begin[d] + count[d])
        wrong = own[y[own] != y_doc[d]]
        for i in wrong[np.argsort(-np.where(y_doc[d], on[wrong], 1 - on[wrong]), kind="stable")].tolist():
            y[i] = y_doc[d]
            held[d] += lines.words[i] if y_doc[d] else -lines.words[i]
            if (held[d] >= share * words[d]) == (y_doc[d] == 1):
                break
    return y


def train(lines: Lines, y_doc: np.ndarray, s: Settings) -> Field:
    theta = ascend(lines, y_doc[lines.doc], np.zeros(lines.x.shape[1] + 6), s, False)
    for _ in range(s.rounds):
        theta = ascend(lines, completed(lines, lines.content(theta), y_doc, s.content_share), theta, s, True)
    return lines.field(theta)


def fit(docs: DataFrame, labels: DataFrame, settings: Settings = Settings(), label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text") -> Field:
    known = labels.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(label_col).cast("int").alias("label")).where("doc_id IS NOT NULL AND label IN (0, 1)")
    picked = known.orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(settings.sample)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, block in blocks(batch.column(2)):
                c = Counts(block)
                edges = np.searchsorted(c.line_doc, np.arange(block.n_docs + 1))
                own = [np.column_stack([c.features[a:b], c.line_words[a:b]]).astype(np.float32).tobytes() for a, b in zip(edges, edges[1:], strict=False)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, block.n_docs), batch.column(1).slice(first, block.n_docs), batch.column(3).slice(first, block.n_docs), pa.array(own, pa.binary())], names=["doc_id", "label", "tie", "lines"])

    texts = id_and_text(docs, id_col, text_col).join(F.broadcast(picked), "doc_id").select("doc_id", "label", "text", F.xxhash64("text").alias("tie"))  # at most ``sample`` ids
    held = texts.mapInArrow(lean(task), "doc_id bigint, label int, tie bigint, lines binary").where("length(lines) > 0")
    rows = held.orderBy(F.xxhash64("doc_id"), "doc_id", "label", "tie").limit(settings.sample).collect()
    y_doc = np.array([r["label"] for r in rows], np.int64)
    if len(np.unique(y_doc)) < 2:
        return Field(np.zeros(len(FEATURES)), np.zeros((2, 2)), np.zeros(2))
    each = [np.frombuffer(r["lines"], np.float32).reshape(-1, len(FEATURES) + 1).astype(np.float64) for r in rows]
    every = np.concatenate(each)
    return train(Lines(every[:, :-1], every[:, -1], np.repeat(np.arange(len(each)), [len(e) for e in each]), len(each), settings.stretch), y_doc, settings)


SCHEMA = pa.schema([("doc_id", pa.int64()), *((n, pa.int64()) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_content_words", "n_lines", "n_content_lines")), ("base_failed", pa.bool_()), ("kept", pa.bool_())])


def verdict(c: Counts, content: np.ndarray, settings: Settings) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words in content lines, whether the base rules fail, and whether the text is kept."""
    n_content = np.bincount(c.line_doc, weights=c.line_words * content, minlength=len(c.n_words)).astype(np.int64)
    failed = (c.n_words < LEAST_WORDS) | (100 * c.n_repeat_words > MOST_REPEATED * c.n_words)
    return n_content, failed, ~failed & (n_content >= settings.content_share * c.n_words)


def judge(docs: DataFrame, field: Field, settings: Settings = Settings(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The base counts, the words in content lines, ``base_failed`` and ``kept`` for every document."""
    shared = docs.sparkSession.sparkContext.broadcast(field)  # some dozens of numbers

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, block in blocks(batch.column(1)):
                c = Counts(block)
                content = viterbi(c.features @ shared.value.unary, c.line_doc, block.n_docs, shared.value)
                n_content, failed, kept = verdict(c, content, settings)
                lines = [np.bincount(c.line_doc, minlength=block.n_docs), np.bincount(c.line_doc[content == 1], minlength=block.n_docs)]
                columns = [c.n_words, c.word_chars, c.n_symbols, c.n_dup_lines, c.n_repeat_words, n_content, *lines]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, block.n_docs), *(pa.array(x.astype(np.int64)) for x in columns), pa.array(failed), pa.array(kept)], schema=SCHEMA)

    return id_and_text(docs, id_col, text_col).mapInArrow(lean(task), "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, n_content_words bigint, n_lines bigint, n_content_lines bigint, base_failed boolean, kept boolean")


def keep_good(docs: DataFrame, field: Field, settings: Settings = Settings(), text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` that ``judge`` keeps, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(field)
    small_batches(docs.sparkSession)
    at = docs.columns.index(text_col)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept = []
            for _, block in blocks(batch.column(at)):
                c = Counts(block)
                content = viterbi(c.features @ shared.value.unary, c.line_doc, block.n_docs, shared.value)
                kept.append(verdict(c, content, settings)[2])
            if kept:
                yield batch.filter(pa.array(np.concatenate(kept)))

    return docs.mapInArrow(lean(task), docs.schema)
