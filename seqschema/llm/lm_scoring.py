"""Cross-entropy difference of matched n-gram models.

Two interpolated bigram models over the same words are counted over the whole corpus: the background model on every
document, the target model on the documents labelled good. Both use the same smoothing weights; a document's own counts
are taken out of the models before it is scored, so that documents of the target sample are judged like any other. A
document's score is the mean over its words of target loss less background loss, in nats: low means closer to the target.

Every word and pair has a count of its own, under a 64-bit number, however many there are; a word precedes another as
often as it occurs without ending a document, so ends are counted beside the words. Documents are packed
into blocks of bounded size. A block sends the counts of its distinct numbers, sorted and packed, to slices of the number
range; a slice adds up what all blocks sent and answers each block with the totals in the block's own order; the block's
documents are then scored. A number is sent once by a block, so a frequent word is no hot key, and the number of slices
grows with the text, so that a slice has a bounded size. The uniform estimate that smooths both models is a constant,
one in 2**WORD_BITS; it is no size of a table.

Defined results: words are the lower-cased runs between ASCII white space; null, empty and blank texts have no words,
losses null and score null. Without any target document both models are uniform plus background, so every difference
is that of the smoothing alone. Repeated rows count as often as they occur.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from seqschema.llm.common import bound_batches, written
from seqschema.llm.ngram_tables import mix, word_numbers

#: The uniform estimate is one in 2**WORD_BITS; weights of bigram, word and uniform estimates.
WORD_BITS, WEIGHTS = 18, (0.5, 0.4, 0.1)
#: Bytes of text of a block, and of all texts for each slice of the number range.
BLOCK_BYTES, SLICE_BYTES = 8 << 20, 10 << 20
#: Counts of a number: occurrences and, for words, ends of documents, over all documents and over the target's.
COUNTS = ("background", "background_ends", "target", "target_ends")
PACKED = ", ".join(f"{c} binary" for c in COUNTS)


def _numbered(text: str) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Word, pair and preceding word's numbers, by parts of a text; the first word follows the number zero."""
    before = np.uint64(0)
    for n in word_numbers(text.lower().encode()):
        prev = np.concatenate(([before], n[:-1]))
        before = n[-1]
        yield n, mix(prev, n, 64), prev


def pack(values: np.ndarray) -> bytes:
    """Unsigned numbers as planes of bytes, as many as the largest needs."""
    width = max(1, (int(values.max(initial=0)).bit_length() + 7) // 8)
    return bytes([width]) + values.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()


def unpack(data: bytes) -> np.ndarray:
    planes = np.frombuffer(data, np.uint8, offset=1).reshape(data[0], -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, : data[0]] = planes.T
    return out.reshape(-1).view("<u8")


def pack_blocks(docs: DataFrame, text_col: str, is_target: str) -> DataFrame:
    """One row for each block: block, bytes of text, words and documents with words, of all and of the target, and the
    documents (an Arrow stream)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, nth, held, sums = TaskContext.get().partitionId(), 0, [], [0] * 5

        def out():
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, held[0].schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as to:
                for x in held:
                    to.write_batch(x)
            values = [(task << 32) + nth, *sums]
            return pa.RecordBatch.from_arrays([*(pa.array([x], pa.int64()) for x in values), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["block", "size", "words", "texts", "good_words", "good_texts", "documents"])

        for batch in batches:
            start = 0
            good = batch.column(batch.schema.get_field_index(is_target)).to_pylist()
            for i, text in enumerate(batch.column(batch.schema.get_field_index(text_col)).to_pylist()):
                data = (text or "").lower().encode()
                n = len(data.split())
                own = (n, int(n > 0))
                sums = [x + y for x, y in zip(sums, (len(data), *own, *(own if good[i] else (0, 0))), strict=True)]
                if sums[0] >= BLOCK_BYTES:
                    held.append(batch.slice(start, i + 1 - start))
                    start = i + 1
                    yield out()
                    nth, held, sums = nth + 1, [], [0] * 5
            if start < batch.num_rows:
                held.append(batch.slice(start))
        if held:
            yield out()

    return docs.mapInArrow(run, "block bigint, size bigint, words bigint, texts bigint, good_words bigint, good_texts bigint, documents binary")


def open_block(data: bytes, text_col: str, is_target: str):
    """The documents, which are of the target, how many words each has, the block's distinct numbers in order, and for
    each document the places of its words and then of its pairs in them."""
    table = pa.ipc.open_stream(data).read_all()
    parts, sizes = [], []
    for text in table.column(text_col).to_pylist():
        got = list(_numbered(text)) if text else []
        sizes.append(sum(len(x[0]) for x in got))
        parts += [x[k] for k in range(2) for x in got]
    good = np.array([bool(x) for x in table.column(is_target).to_pylist()], bool)
    sizes = np.array(sizes, np.int64)
    numbers, places = np.unique(np.concatenate(parts) if parts else np.zeros(0, np.uint64), return_inverse=True)
    return table, good, sizes, numbers, places


def total_counts(blocks: DataFrame, bits: int, text_col: str, is_target: str) -> DataFrame:
    """(block, slice, COUNTS): packed totals of the block's numbers in that slice, in their order."""

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bounds = (np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)) if bits else np.zeros(0, np.uint64)
        for batch in batches:
            for block, data in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                _, good, sizes, numbers, places = open_block(data, text_col, is_target)
                if not len(numbers):
                    continue
                ends = np.cumsum(2 * sizes) - sizes - 1
                some = sizes > 0
                sets = (places, places[ends[some]], places[np.repeat(good, 2 * sizes)], places[ends[some & good]])
                counts = [np.bincount(x, minlength=len(numbers)) for x in sets]
                cuts = [0, *np.searchsorted(numbers, bounds).tolist(), len(numbers)]
                rows = [(i, block, int(numbers[a]), pack(np.diff(numbers[a:b])), *(pack(c[a:b]) for c in counts)) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if b > a]
                kinds = [pa.int32(), pa.int64(), pa.uint64(), *[pa.binary()] * 5]
                cols = [pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)]
                cols[2] = pa.array(np.array([r[2] for r in rows], np.uint64).view(np.int64))
                yield pa.RecordBatch.from_arrays(cols, names=["slice", "block", "first", "steps", *COUNTS])

    def answer(table: pa.Table) -> pa.Table:
        cols = {c: table.column(c).to_pylist() for c in table.column_names}
        numbers = [np.cumsum(np.concatenate((np.array([first], np.int64).view(np.uint64), unpack(steps))), dtype=np.uint64) for first, steps in zip(cols["first"], cols["steps"], strict=True)]
        ends = np.cumsum([len(x) for x in numbers])[:-1]
        _, places = np.unique(np.concatenate(numbers), return_inverse=True)
        del numbers
        out = []
        for side in COUNTS:
            given = np.concatenate([unpack(x) for x in cols[side]])
            # sums of whole numbers stay exact below 2**53
            total = np.bincount(places, weights=given).astype(np.uint64)
            out.append(pa.array([pack(x) for x in np.split(total[places], ends)], pa.binary()))
        return pa.table([pa.array(cols["block"], pa.int64()), pa.array(cols["slice"], pa.int32()), *out], names=["block", "slice", *COUNTS])

    asked = blocks.select("block", "documents").mapInArrow(ask, f"slice int, block bigint, first bigint, steps binary, {PACKED}")
    return asked.groupBy("slice").applyInArrow(answer, f"block bigint, slice int, {PACKED}")


def losses(words, pairs, contexts, total: int, weights=WEIGHTS) -> np.ndarray:
    """Loss of each word from the counts of the word, of its pair and of its context."""
    plain = words / max(1, total)
    given = np.where(contexts > 0, np.minimum(1.0, pairs / np.maximum(contexts, 1)), plain)
    return -np.log(weights[0] * given + weights[1] * plain + weights[2] / (1 << WORD_BITS))


def score_documents(docs: DataFrame, is_target: str, text_col: str = "text", keep=("doc_id",)) -> DataFrame:
    """n_words, target_loss, background_loss and score (their difference), all rounded to 9 places."""
    bound_batches(docs.sparkSession)
    fields = [("n_words", T.LongType()), ("target_loss", T.DoubleType()), ("background_loss", T.DoubleType()), ("score", T.DoubleType())]
    keep = [c for c in keep if c not in {n for n, _ in fields}]
    src = docs.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*keep, text_col, is_target])])
    blocks = written(pack_blocks(src, text_col, is_target), "lm-blocks")
    size, *totals = (int(x or 0) for x in blocks.agg(*(F.sum(c) for c in ("size", "words", "texts", "good_words", "good_texts"))).first())
    bits = max(0, (size // SLICE_BYTES).bit_length())
    counts = total_counts(blocks, bits, text_col, is_target)

    def score(block: pa.Table, answers: pa.Table) -> pa.Table:
        table, good, sizes, numbers, places = open_block(block.column("documents")[0].as_py(), text_col, is_target)
        order = pc.sort_indices(answers.column("slice"))
        sides = [np.concatenate([np.zeros(0, np.uint64), *(unpack(x) for x in answers.column(c).take(order).to_pylist())]).astype(np.int64) for c in COUNTS]
        if any(len(x) != len(numbers) for x in sides):
            raise ValueError("a block's counts are not complete")
        out, at = [], 0
        for n, is_good in zip(sizes.tolist(), good.tolist(), strict=True):
            if not n:
                out.append((0, None, None, None))
                continue
            here = places[at : at + 2 * n]
            at += 2 * n
            _, back, times = np.unique(here, return_inverse=True, return_counts=True)
            own, words = times[back], here[:n]
            is_last = words == words[-1]

            def loss(k, less):
                counted = sides[k][here] - (own if less else 0)
                # the word before: how often it occurs less how often it ends a document; the first word follows nothing
                follows = counted[:n] - sides[k + 1][words] + (is_last if less else 0)
                contexts = np.concatenate(([totals[k + 1] - less], follows[:-1]))
                return float(losses(counted[:n], counted[n:], contexts, totals[k] - (n if less else 0)).mean())

            a, b = loss(2, is_good), loss(0, True)
            out.append((n, round(a, 9), round(b, 9), round(a - b, 9)))
        kinds = [pa.int64(), *[pa.float64()] * 3]
        return pa.table([*(table.column(c) for c in keep), *(pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True))], names=[*keep, *(n for n, _ in fields)])

    schema = T.StructType([src.schema[c] for c in keep] + [T.StructField(n, t) for n, t in fields])
    return blocks.select("block", "documents").groupBy("block").cogroup(counts.groupBy("block")).applyInArrow(score, schema)
