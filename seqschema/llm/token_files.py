"""Token ids in Arrow stream files, with random access to sequences of equal length.

Texts are encoded in one pass; the packed ids, not the texts, then go to shards by ranges of doc_id and are sorted. The
number of shards grows with the bytes of text. Each shard is one stream of ids in ascending doc_id order, cut into
sequences of SEQUENCE ids: a record batch holds BATCH sequences (the last one the rest) as a fixed-size list of ids and a
fixed-size list of mask bits (false where the shard's last sequence is padded). All batches but the last have the same
length in bytes, so the place of any sequence follows from its number, and read through a memory map it is a slice of
the file, without a copy. A second stream beside it lists the shard's documents: doc_id, first id, number of ids. Files
are written under a temporary name and renamed, so a lost or repeated task leaves whole files only.

The tokenizers library encodes. Where the tokenizer file has the steps this module knows, the characters of a batch are
looked up in tables of their class and lower case, cut into pretokens by array operations and made distinct; the
library's model gets those it has not seen, many at a time with spaces between them, and the ids of all are gathered.
Only characters for which a probe of the library gives this class and this lower case, alone and beside others, are in
the tables. A text with another one, or with a special token, is cut at white space; its strings without such a
character take the same way, the others are encoded by all steps of the library, whose offsets say which ids are whose.
This gives the ids of the whole text, because neither its normaliser nor its pretokens reach across white space.

Defined results: null counts as the empty text (just the end id). Equal doc_ids follow each other, by the crc32 of
their ids, then by the ids; an id that holds more rows than a shard has shards of its own by ranges of that crc32. A
null doc_id comes first, in the same way. Repeated rows are written as often as they occur.
"""

from __future__ import annotations

import functools
import itertools
import json
import os
import re
import unicodedata
import uuid
import zlib
from collections import defaultdict
from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.fs
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from seqschema.llm.common import append_columns, bound_batches, fresh_dir, written

SEQUENCE, BATCH, END = 2048, 256, 1
#: Bytes of text for each shard. Units a worker remembers, the longest of them, units encoded in one call.
SHARD_BYTES, KNOWN, LONG, CALL = 1 << 30, 600_000, 64, 256
#: The tokenizer file's steps before the model.
STEPS = ["NFC", r"\s+", "Lowercase"], r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
PRETOKENS = re.compile(r"[^\W\d_]+|\d|'(?:s|t|re|ve|m|ll|d)|(?:[^\s\w]|_)+")
#: Classes of characters; those not yet looked up are zero.
SPACE, LETTER, DIGIT, OTHER, ODD = range(1, 6)

#: White space of Python that the tokenizer takes for symbols: texts that hold it are cut by the tokenizer's own rule.
ODD_SPACES = re.compile("[\x1c-\x1f]")
SPACES = re.compile(r"[^\S\x1c-\x1f]+")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordEncoder:
    def __init__(self, path: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.library, self.model = Tokenizer.from_file(path), Tokenizer.from_file(path)
        for x in (self.library, self.model):
            x.no_truncation()
            x.no_padding()
        # the model alone, for pretokens in lower case between spaces
        self.model.normalizer = None
        self.model.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        steps = [x["pattern"]["Regex"] if x["type"] == "Replace" else x["type"] for x in (spec["normalizer"] or {}).get("normalizers", [])]
        split = [x["pattern"]["Regex"] for x in (spec["pre_tokenizer"] or {}).get("pretokenizers", []) if x["type"] == "Split"]
        self.knows_steps = (steps, *split) == STEPS
        self.special = re.compile("|".join(re.escape(x["content"]) for x in spec["added_tokens"]) or r"(?!)")
        self.kind = np.uint16 if self.library.get_vocab_size() <= 1 << 16 else np.uint32
        self.classes, self.lower = np.zeros(0x110000, np.uint8), np.arange(0x110000, dtype=np.uint32)
        self.forget()

    def forget(self) -> None:
        """Numbers of pretokens (in UTF-32) and of strings, and by number where their ids are. Number 0 is the end id."""
        self.number: dict[bytes | str, int] = defaultdict(itertools.count(1).__next__)
        self.first, self.length = np.zeros(1, np.int64), np.ones(1, np.int64)
        self.flat = np.array([END], self.kind)

    def look_up(self, c: str) -> None:
        """Class and lower case of a character, where the library agrees and never composes it with another."""
        at = ord(c)
        if c.isspace():
            self.classes[at] = ODD if ODD_SPACES.match(c) else SPACE
            return
        probe = f"a{c}1{c}!{c}'{c}{c}a"
        low = self.library.normalizer.normalize_str(probe)
        split = [low[a:b] for _, (a, b) in self.library.pre_tokenizer.pre_tokenize_str(low)]
        alone = c.isprintable() and unicodedata.category(c)[0] != "M" and not "\u1100" <= c <= "\u11ff" and len(c.lower()) == 1
        if not alone or low != probe.lower() or split != PRETOKENS.findall(low):
            self.classes[at] = ODD
            return
        self.classes[at] = DIGIT if c.isdecimal() else LETTER if c.isalnum() else OTHER
        self.lower[at] = ord(c.lower())

    def classed(self, codes: np.ndarray) -> np.ndarray:
        """The class of each character."""
        if not self.knows_steps:
            return np.full(len(codes), ODD, np.uint8)
        found = self.classes[codes]
        if not found.all():
            for c in np.unique(codes[found == 0]).tolist():
                self.look_up(chr(c))
            found = self.classes[codes]
        return found

    def numbers(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """The place and the number of each pretoken of a text that has nothing odd."""
        codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        classes, low = self.classed(codes), self.lower[codes]
        begins = np.ones(len(codes), bool)
        begins[1:] = (classes[1:] != classes[:-1]) | (classes[1:] == DIGIT)
        quotes = np.flatnonzero(begins & (low == ord("'")))
        one, two = (low[np.minimum(quotes + k, len(low) - 1)] for k in (1, 2))
        pairs = np.isin(one * np.uint32(256) + two, [ord(a) << 8 | ord(b) for a, b in ("re", "ve", "ll")]) & (quotes + 2 < len(low)) & (one < 256) & (two < 256)
        short = np.isin(one, [ord(c) for c in "stmd"]) & (quotes + 1 < len(low))
        begins[quotes[pairs | short] + 1] = False
        ends = np.concatenate((quotes[short] + 2, quotes[pairs] + 3))
        begins[ends[ends < len(low)]] = True
        words = classes != SPACE
        places = np.flatnonzero(begins & words)
        data = low[words]
        edges = np.append(np.flatnonzero(begins[words]), len(data)).astype(np.int64) * 4
        pieces = pa.Array.from_buffers(pa.large_binary(), len(places), [None, pa.py_buffer(edges), pa.py_buffer(data)]).dictionary_encode()
        distinct = pieces.dictionary.to_pylist()
        return places, np.fromiter(map(self.number.__getitem__, distinct), np.int32, len(distinct))[pieces.indices.to_numpy()]

    def learn(self, units: Sequence[bytes | str]) -> None:
        """The ids of pretokens and strings that just got their numbers, in this order."""
        first, length, flat = np.zeros(len(units), np.int64), np.zeros(len(units), np.int64), [self.flat]
        end = len(self.flat)
        for kind, encoder in ((bytes, self.model), (str, self.library)):
            which = [k for k, u in enumerate(units) if isinstance(u, kind)]
            for k in range(0, len(which), CALL):
                at = which[k : k + CALL]
                some = [units[i] for i in at]
                got = encoder.encode(b" \0\0\0".join(some).decode("utf-32-le") if kind is bytes else " ".join(some), add_special_tokens=False)
                if kind is bytes:
                    owner = np.array(got.word_ids, np.int64)
                else:
                    start = np.fromiter((a for a, _ in got.offsets), np.int64, len(got.ids))
                    owner = np.searchsorted(np.cumsum([len(x) + 1 for x in some]), start, "right")
                n = np.bincount(owner, minlength=len(some))
                length[at], first[at] = n, end + np.cumsum(n) - n
                flat.append(np.array(got.ids, self.kind))
                end += len(got.ids)
        self.first, self.length, self.flat = np.concatenate((self.first, first)), np.concatenate((self.length, length)), np.concatenate(flat)

    def odd(self, text: str) -> bool:
        return bool(self.special.search(text)) or bool((self.classed(np.frombuffer(text.encode("utf-32-le"), np.uint32)) == ODD).any())

    def strings(self, text: str) -> np.ndarray:
        """The numbers of an odd text: of the pretokens of its strings, but of the whole string where that is odd."""
        out = [np.zeros(0, np.int32)]
        pieces = list(filter(None, SPACES.split(text))) if ODD_SPACES.search(text) else text.split()
        for odd, some in itertools.groupby(pieces, self.odd):
            if odd:
                out.append(np.fromiter(map(self.number.__getitem__, some), np.int32))
            else:
                out.append(self.numbers(" ".join(some))[1])
        return np.concatenate(out)

    def encode(self, texts: Sequence[str]) -> list[bytes]:
        """The ids of each text and the end id, as little-endian numbers."""
        if max(len(self.length), len(self.flat) >> 4) > KNOWN:
            self.forget()
        before = len(self.number)
        joined = "\n".join(texts)
        odd = set(itertools.compress(range(len(texts)), map(self.odd, texts))) if self.odd(joined) else set()
        plain = ["" if k in odd else t for k, t in enumerate(texts)] if odd else texts
        places, numbers = self.numbers("\n".join(plain) if odd else joined)
        edges = np.searchsorted(places, np.cumsum([len(t) + 1 for t in plain], dtype=np.int64))
        if odd:
            parts = np.split(numbers, edges[:-1])
            parts = [self.strings(t) if k in odd else parts[k] for k, t in enumerate(texts)]
            numbers, edges = np.concatenate(parts), np.cumsum([len(x) for x in parts], dtype=np.int64)
        new = list(itertools.islice(reversed(self.number), len(self.number) - before))[::-1]
        self.learn(new)
        for u in new:
            if len(u) > (LONG if isinstance(u, str) else 4 * LONG):
                del self.number[u]
        every = np.insert(numbers, edges, 0)
        length = self.length[every]
        after = np.cumsum(length)
        data = self.flat[np.repeat(self.first[every] - after + length, length) + np.arange(length.sum())].tobytes()
        cuts = after[edges + np.arange(len(edges))] * self.flat.itemsize
        return [data[a:b] for a, b in itertools.pairwise([0, *cuts.tolist()])]


@functools.lru_cache(maxsize=2)
def load(path: str) -> WordEncoder:
    return WordEncoder(path)


def store(folder: str) -> tuple[pyarrow.fs.FileSystem, str]:
    """The file system of a folder's address and the path in it."""
    return pyarrow.fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("file:") else f"file://{folder}")


class ShardWriter:
    def __init__(self, folder: str, shard: int, kind: pa.DataType) -> None:
        self.fs, path = store(folder)
        self.fs.create_dir(path)
        self.shard, self.tag, self.path = shard, uuid.uuid4().hex, path
        lists = pa.list_(kind, SEQUENCE), pa.list_(pa.bool_(), SEQUENCE)
        self.kind = kind.to_pandas_dtype()
        self.schema = pa.schema([("ids", lists[0]), ("mask", lists[1])])
        self.doc_schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])
        self.streams = {n: self.fs.open_output_stream(f"{path}/.{n}-{shard:06d}-{self.tag}") for n in ("ids", "docs")}
        self.ids = pa.ipc.new_stream(self.streams["ids"], self.schema)
        self.docs = pa.ipc.new_stream(self.streams["docs"], self.doc_schema)
        self.parts: list[np.ndarray] = []
        self.waiting = self.total = 0

    def add(self, ids: np.ndarray) -> int:
        start = self.total
        self.parts.append(ids.astype(self.kind))
        self.waiting += len(ids)
        self.total += len(ids)
        if self.waiting >= SEQUENCE * BATCH:
            self.flush()
        return start

    def flush(self, last: bool = False) -> None:
        flat = np.concatenate(self.parts) if self.parts else np.zeros(0, self.kind)
        # whole batches only before the last, so that all are of one length
        whole = len(flat) // SEQUENCE * SEQUENCE if last else len(flat) // (SEQUENCE * BATCH) * SEQUENCE * BATCH
        size = whole + (SEQUENCE if last and len(flat) > whole else 0)
        full = np.zeros(size, self.kind)
        full[: min(size, len(flat))] = flat[:size]
        for k in range(0, size, SEQUENCE * BATCH):
            ids = full[k : k + SEQUENCE * BATCH]
            mask = np.arange(k, k + len(ids)) < len(flat)
            self.ids.write_batch(pa.RecordBatch.from_arrays([pa.FixedSizeListArray.from_arrays(pa.array(ids), SEQUENCE), pa.FixedSizeListArray.from_arrays(pa.array(mask), SEQUENCE)], schema=self.schema))
        self.parts = [flat[whole:]] if not last and len(flat) > whole else []
        self.waiting = 0 if last else len(flat) - whole

    def close(self) -> None:
        self.flush(last=True)
        for name, writer in (("ids", self.ids), ("docs", self.docs)):
            writer.close()
            self.streams[name].close()
            self.fs.move(f"{self.path}/.{name}-{self.shard:06d}-{self.tag}", f"{self.path}/{name}-{self.shard:06d}.arrow")


class Ranges:
    """Shards by ranges of doc_id. cuts: quantiles of the ids. A cut that occurs several times is an id with several
    shards' rows: it has shards of its own, after that of the ids below it. Nulls are first."""

    def __init__(self, cuts: Sequence[int], nulls: int) -> None:
        self.nulls = nulls
        self.values, times = np.unique(np.array(cuts, np.int64), return_counts=True)
        self.own = np.where(times > 1, times, 0)
        self.first = nulls + np.concatenate(([0], np.cumsum(1 + self.own)))
        self.number = int(self.first[-1]) + 1

    def shard(self, doc: int | None, crc: int) -> int:
        if doc is None:
            return crc * self.nulls >> 32
        k = int(np.searchsorted(self.values, doc))
        if k < len(self.values) and self.own[k] and self.values[k] == doc:
            return int(self.first[k]) + 1 + (crc * int(self.own[k]) >> 32)
        return int(self.first[k])


def write_token_files(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, folder: str | None = None, shards: int | None = None) -> DataFrame:
    """Write the files; return one row for each: folder, shard, n_tokens (ids in it), before (ids in earlier shards)."""
    spark = docs.sparkSession
    path, folder = path or default_path(), folder or fresh_dir(spark, "tokens")
    src = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    if shards is None:
        size = src.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        shards = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // SHARD_BYTES), 1)
    steps = [k / shards for k in range(1, shards)] or [0.5]
    found = src.agg(F.percentile_approx("doc_id", steps, max(10_000, 20 * shards)).alias("cuts"), F.count("*").alias("rows"), F.count("doc_id").alias("named")).first()
    ranges = Ranges((found["cuts"] or [])[: shards - 1], -(-(found["rows"] - found["named"]) * shards // max(1, found["rows"])))

    def kernel():
        enc, pack = load(path), zstandard.ZstdCompressor(level=1)

        def work(texts, batch):
            ids = enc.encode(texts)
            crcs = [zlib.crc32(x) for x in ids]
            shard = [ranges.shard(d, c) for d, c in zip(batch.column(0).to_pylist(), crcs, strict=True)]
            return [pa.array(shard, pa.int32()), pa.array(crcs, pa.int64()), pa.array(map(pack.compress, ids), pa.binary())]

        return work

    fields = [("shard", T.IntegerType()), ("crc", T.LongType()), ("ids", T.BinaryType())]
    rows = append_columns(src, "text", kernel, fields, ["doc_id"])
    kind = load(path).kind
    bound_batches(spark)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack, writer, listing = zstandard.ZstdDecompressor(), None, []

        def done():
            writer.docs.write_batch(pa.RecordBatch.from_pylist(listing, writer.doc_schema)) if listing else None
            writer.close()
            return pa.RecordBatch.from_arrays([pa.array([writer.shard], pa.int32()), pa.array([writer.total], pa.int64())], names=["shard", "n_tokens"])

        for b in batches:
            for doc, shard, packed in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if writer is None or writer.shard != shard:
                    if writer is not None:
                        yield done()
                        listing = []
                    writer = ShardWriter(folder, shard, pa.from_numpy_dtype(kind))
                ids = np.frombuffer(unpack.decompress(packed), kind)
                listing.append({"doc_id": doc, "start": writer.add(ids), "n_tokens": len(ids)})
                if len(listing) >= 50_000:
                    writer.docs.write_batch(pa.RecordBatch.from_pylist(listing, writer.doc_schema))
                    listing = []
        if writer is not None:
            yield done()

    sorted_rows = rows.repartitionById(ranges.number, F.col("shard")).sortWithinPartitions("shard", "doc_id", "crc", "ids").select("doc_id", "shard", "ids")
    found = written(sorted_rows.mapInArrow(write, "shard int, n_tokens bigint"), "token-manifest").collect()  # a row for each shard
    before, out = 0, []
    for r in sorted(found):
        out.append((folder, r["shard"], r["n_tokens"], before))
        before += r["n_tokens"]
    return spark.createDataFrame(out, "folder string, shard int, n_tokens bigint, before bigint")


def open_stream(folder: str, name: str) -> pa.RecordBatchReader:
    fs, path = store(folder)
    local = isinstance(fs, pyarrow.fs.LocalFileSystem)
    return pa.ipc.open_stream(pa.memory_map(f"{path}/{name}") if local else fs.open_input_stream(f"{path}/{name}"))


def sequence(folder: str, shard: int, number: int) -> tuple[np.ndarray, np.ndarray]:
    """One sequence of a shard and its mask: views of the mapped file for the ids. The first batch's length gives the
    place of every other one."""
    fs, path = store(folder)
    name = f"{path}/ids-{shard:06d}.arrow"
    with pa.memory_map(name) if isinstance(fs, pyarrow.fs.LocalFileSystem) else fs.open_input_file(name) as file:
        schema = pa.ipc.read_schema(file)
        start = file.tell()
        nth, place = divmod(number, BATCH)
        if nth:
            pa.ipc.read_message(file)
            place_of = start + nth * (file.tell() - start)
            if place_of >= file.size():
                raise IndexError(number)
            file.seek(place_of)
        try:
            batch = pa.ipc.read_record_batch(pa.ipc.read_message(file), schema)
        except (EOFError, pa.ArrowInvalid) as e:
            raise IndexError(number) from e
        if place >= batch.num_rows:
            raise IndexError(number)
    lists, masks = (c.values[(c.offset + place) * SEQUENCE :][:SEQUENCE] for c in batch.columns)
    return lists.to_numpy(zero_copy_only=True), masks.to_numpy(zero_copy_only=False)


def read_documents(folder: str, shard: int) -> Iterator[tuple[int | None, int, np.ndarray]]:
    """(doc_id, first id in the shard, ids) of a shard's documents, read batch by batch."""
    batches = iter(open_stream(folder, f"ids-{shard:06d}.arrow"))
    held, begin = np.zeros(0, np.uint16), 0
    for docs in open_stream(folder, f"docs-{shard:06d}.arrow"):
        for doc, start, n in zip(*(c.to_pylist() for c in docs.columns), strict=True):
            more, have = [held[start - begin :]], len(held) - (start - begin)
            while have < n:
                flat = next(batches).column(0).flatten().to_numpy()
                more.append(flat)
                have += len(flat)
            if len(more) > 1 or start > begin + (1 << 20):
                held, begin = np.concatenate(more), start
            yield doc, start, held[start - begin : start - begin + n]


def read_digests(files: DataFrame) -> DataFrame:
    """From the files: doc_id, start (ids of all documents before it), n_tokens, ids_crc32."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows(out):
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

        for b in batches:
            for folder, shard, _, before in zip(*(c.to_pylist() for c in b.columns), strict=True):
                out = []
                for doc, start, ids in read_documents(folder, shard):
                    out.append((doc, before + start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    if len(out) >= 20_000:
                        yield rows(out)
                        out = []
                if out:
                    yield rows(out)

    shards = max(1, files.count())
    spread = files.select("folder", "shard", "n_tokens", "before").repartition(min(shards, 2000), "shard")
    return spread.mapInArrow(read, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")
