"""Quality rules: counts of a text's form, and a hashed n-gram likelihood ratio.

The form counts are exact and reject a document by fixed limits. The method then compares two multinomials over hashed
features (words and word pairs in buckets): the trusted target, documents labelled good and not toxic, and the raw
corpus, every document. A document's ratio is the mean log-likelihood ratio of its features, under multinomials without
its own counts: a trusted document is judged as if it were not trusted, so that its ratio can be compared with that of
any other document at any size of the corpus. Every document below one fixed threshold is rejected, without any random
draw.

The threshold is set from these ratios of trusted documents: their mean less `spread` standard deviations, both summed
over all of them. Trusted documents are what the filter must not lose.

Defined results: words are the runs between ASCII white space; null, empty and blank texts have none, ratio null, and
fail the base rules. Without trusted documents the method keeps all that pass the base rules. Repeated rows count and
are judged as often as they occur.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from seqschema.llm.common import append_columns
from seqschema.llm.ngram_tables import mix, total_tables, word_numbers

#: Fixed values of the base rules.
LEAST_WORDS, MOST_REPEATED_PERCENT, SYMBOLS = 50, 50, "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"

#: Bits of the feature table, pseudo-counts for each bucket, how far below the trusted mean the threshold lies.
BITS, SMOOTHING, SPREAD = 17, 1.0, 5.0
#: Ratios are summed as integers in millionths, so that sums do not depend on the order of tasks.
SCALE = 1_000_000


def repeated_words(words: list[bytes]) -> int:
    """Words inside any window of three words that occurs twice or more in the text."""
    n = len(words)
    if n < 4:
        return 0
    own: dict[bytes, int] = {}
    ids = np.fromiter(map(own.setdefault, words, itertools.count()), np.int64, n)
    if n < 2_000_000:
        code = (ids[:-2] * n + ids[1:-1]) * n + ids[2:]
    else:
        two = np.unique(ids[:-1] * n + ids[1:], return_inverse=True)[1].astype(np.int64)
        code = two[:-1] * n + ids[2:]
    ordered = np.sort(code)
    if not (ordered[1:] == ordered[:-1]).any():
        return 0
    _, back, times = np.unique(code, return_inverse=True, return_counts=True)
    again = times[back] > 1
    covered = np.zeros(n, bool)
    for shift in range(3):
        covered[shift : shift + n - 2] |= again
    return int(covered.sum())


def form(text: str, words: list[bytes]) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    lines = [x for x in text.split("\n") if x.strip(SPACES)]
    return (
        len(words), len(text) - sum(map(text.count, SPACES)), sum(map(text.count, SYMBOLS)),
        len(lines) - len(set(lines)), repeated_words(words),
    )


def base_failed(n_words: int, n_repeat_words: int) -> bool:
    return n_words < LEAST_WORDS or 100 * n_repeat_words > MOST_REPEATED_PERCENT * n_words


def features(text: str) -> Iterator[np.ndarray]:
    """Buckets of the words and of the pairs of neighbours, by parts of a text."""
    before = None
    for n in word_numbers(text.encode()):
        yield (n >> np.uint64(64 - BITS)).astype(np.int64)
        both = n if before is None else np.concatenate(([before], n))
        before = n[-1]
        if len(both) > 1:
            yield mix(both[:-1], both[1:], BITS).astype(np.int64)


def count_features(docs: DataFrame, is_trusted: str, text_col: str) -> dict[str, np.ndarray]:
    def add():
        def work(batch, tables):
            texts, good = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for k in (0, 1):
                got = [x for t, g in zip(texts, good, strict=True) if t and (not k or g) for x in features(t)]
                if got:
                    tables[k] += np.bincount(np.concatenate(got), minlength=1 << BITS)

        return work

    return total_tables(docs, [text_col, is_trusted], ["raw", "trusted"], [1 << BITS] * 2, add)


def own_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """The buckets of a text's features, and how often it has each. A very long text is added up part by part."""
    held, dense, size = [], None, 0
    for f in features(text):
        held.append(f)
        size += len(f)
        if size > 1 << BITS:
            counts = np.bincount(np.concatenate(held), minlength=1 << BITS)
            dense, held, size = counts if dense is None else dense + counts, [], 0
    if dense is None:
        return np.unique(np.concatenate(held), return_counts=True) if held else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    if held:
        dense = dense + np.bincount(np.concatenate(held), minlength=1 << BITS)
    found = np.flatnonzero(dense)
    return found, dense[found]


class Ratio:
    """log p(trusted) - log p(raw), the mean over a text's features, without the text's own counts. The trusted
    multinomial is smoothed towards the raw one."""

    def __init__(self, raw: np.ndarray, trusted: np.ndarray, smoothing: float = SMOOTHING) -> None:
        self.raw, self.trusted, self.smoothing = raw, trusted, smoothing
        self.all, self.good = int(raw.sum()), int(trusted.sum())

    def of(self, text: str, is_trusted: bool) -> float | None:
        buckets, times = own_counts(text)
        n = int(times.sum())
        if not n:
            return None
        weight = self.smoothing * len(self.raw)
        raw = (self.raw[buckets] - times + self.smoothing) / (self.all - n + weight)
        own = times if is_trusted else 0
        trusted = (self.trusted[buckets] - own + weight * raw) / (self.good - (n if is_trusted else 0) + weight)
        return float((times * np.log(trusted / raw)).sum()) / n


def judge(docs: DataFrame, is_trusted: str, text_col: str = "text", keep=("doc_id",), spread: float = SPREAD, prefix: str = "") -> DataFrame:
    """The kept columns with the form counts, base_failed, ratio and kept."""
    spark = docs.sparkSession
    tables = count_features(docs, is_trusted, text_col)
    sent = spark.sparkContext.broadcast(Ratio(tables["raw"], tables["trusted"]))

    def spread_of_trusted():
        ratio = sent.value

        def work(batch, tables):
            for text, good in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if text and good and (r := ratio.of(text, True)) is not None:
                    r = round(r * SCALE)
                    tables[0] += np.array([1, r, r * r // SCALE], np.int64)

        return work

    trusted = docs.where(F.col(is_trusted))
    n, total, squares = (int(x) for x in total_tables(trusted, [text_col, is_trusted], ["sums"], [3], spread_of_trusted)["sums"])
    threshold = None
    if n:
        mean = total / n / SCALE
        threshold = mean - spread * max(1e-6, squares / n / SCALE - mean * mean) ** 0.5

    def kernel():
        of = sent.value.of

        def work(texts, batch):
            rows = []
            for text, good in zip(texts, batch.column(batch.schema.get_field_index(is_trusted)).to_pylist(), strict=True):
                words = text.encode().split()
                counts = form(text, words)
                failed, ratio = base_failed(counts[0], counts[4]), of(text, bool(good))
                kept = not failed and (threshold is None or ratio >= threshold)
                rows.append((*counts, failed, None if ratio is None else round(ratio, 9), kept))
            kinds = [pa.int64()] * 5 + [pa.bool_(), pa.float64(), pa.bool_()]
            return [pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)]

        return work

    fields = [(prefix + x, T.LongType()) for x in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
    fields += [(prefix + "base_failed", T.BooleanType()), (prefix + "ratio", T.DoubleType()), (prefix + "kept", T.BooleanType())]
    return append_columns(docs, text_col, kernel, fields, [c for c in keep if c != is_trusted], [is_trusted])
