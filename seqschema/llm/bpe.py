"""Byte-level BPE encoding and decoding without merge queues.

An Aho-Corasick automaton over the vocabulary gives, for each position of a pretoken, the longest token that starts
there. The encoder walks left to right with the longest token; a token may follow another one only if the two are
compatible, that is, if BPE would leave them apart. Where no token fits it falls back to the next shorter prefix token,
then to the previous position. The result is what the merges give, in time linear in the text. Pairs once judged are
kept in a table. Decoding concatenates slices of one byte blob by an offset table.

Texts: null counts as the empty text (no tokens). Texts of any length are cut where no pretoken can cross (a space
after a non-space), so memory is bounded by the cut size unless one pretoken alone is longer. Special tokens of the
tokenizer file that occur in a text become their ids, as the tokenizers library does by default.
"""

from __future__ import annotations

import functools
import hashlib
import json
import re
from array import array
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from tokenizers import Tokenizer

from seqschema.llm.common import append_columns

#: The pretoken pattern of byte-level BPE, in the classes of Python's re. Characters that re
#: and the tokenizer's own matcher put into different classes are found by a probe; texts that hold one go to the latter.
PRETOKENS = r"'(?:s|t|re|ve|m|ll|d)| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+"
ASCII_PRETOKENS = r"'(?:s|t|re|ve|m|ll|d)| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r A-Za-z0-9]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+"

#: Distinct pretokens a worker remembers, the longest pretoken worth remembering, code points encoded at a time.
CACHE_ENTRIES, CACHE_LENGTH, CUT = 250_000, 64, 1 << 20


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def printable_bytes() -> dict[str, int]:
    """The character that stands for each byte in vocabulary files: itself if it is visible Latin-1, else one from U+0100 on."""
    table, spare = {}, 256
    for b in range(256):
        if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174:
            table[chr(b)] = b
        else:
            table[chr(spare)] = b
            spare += 1
    return table


class OffsetTable:
    """Byte strings by number, laid end to end; render() concatenates those of a list of numbers."""

    def __init__(self, items: list[bytes]) -> None:
        self.offsets = np.zeros(len(items) + 1, np.int64)
        np.cumsum([len(x) for x in items], out=self.offsets[1:])
        self.blob = np.frombuffer(b"".join(items), np.uint8)

    def render(self, ids: np.ndarray, block: int = 1 << 18) -> Iterator[np.ndarray]:
        for k in range(0, len(ids), block):
            part = ids[k : k + block]
            start = self.offsets[part]
            size = self.offsets[part + 1] - start
            end = np.cumsum(size)
            yield self.blob[np.arange(end[-1]) + np.repeat(start - (end - size), size)]


class PairEncoder:
    """Tokens are numbered by merge order inside (bytes first), so that a smaller number means an earlier merge."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        byte_of = printable_bytes()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        vocab = spec["model"]["vocab"]
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
        order = [c for c, _ in sorted(byte_of.items(), key=lambda x: x[1])]
        number = {c: b for b, c in enumerate(order)}
        self.parts: list[tuple[int, int]] = [(b, b) for b in range(256)]
        self.merged: dict[tuple[int, int], int] = {}
        for left, right in merges:
            new = len(order)
            order.append(left + right)
            number[left + right] = new
            self.parts.append((number[left], number[right]))
            self.merged[number[left], number[right]] = new
        if len(number) != len(order):
            raise ValueError("two merges make the same token: pair compatibility by merge order does not hold")
        self.keys = [bytes(byte_of[c] for c in x).decode("latin-1") for x in order]
        self.sizes = [len(x) for x in self.keys]
        self.external = [vocab[x] for x in order]
        self.by_key = {k: i for i, k in enumerate(self.keys)}
        self.matcher = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        for i, k in enumerate(self.keys):
            self.matcher.add_word(k, i)
        self.matcher.make_automaton()
        self.shorter: list[int | None] = [-1] * len(order)
        self.compatible: dict[int, bool] = {}
        self.find_any = re.compile(PRETOKENS).findall
        self.find_ascii = re.compile(ASCII_PRETOKENS).findall
        self.library = Tokenizer.from_file(path).pre_tokenizer
        self.agreed: dict[str, bool] = {}
        self.cut_at = re.compile(r"(?<=\S) ")
        self.split = re.compile("|".join(re.escape(x) for x in sorted(self.special, key=len, reverse=True))) if self.special else None
        spelled: list[bytes] = [b""] * (1 + max([*self.external, *self.special.values()]))
        for i, k in zip(self.external, self.keys, strict=True):
            spelled[i] = k.encode("latin-1")
        for x, i in self.special.items():
            spelled[i] = x.encode()
        self.spelled = OffsetTable(spelled)
        self.decimal = OffsetTable([b"%d," % i for i in range(len(spelled))])
        self.cache = Remembered(lambda piece: array("I", self.pretoken(piece)).tobytes())

    def prefix(self, token: int) -> int | None:
        """The longest token that is a proper prefix of this one."""
        if (known := self.shorter[token]) != -1:
            return known
        key, found = self.keys[token], None
        for size in range(len(key) - 1, 0, -1):
            if (found := self.by_key.get(key[:size])) is not None:
                break
        self.shorter[token] = found
        return found

    def may_follow(self, left: int, right: int) -> bool:
        code = left * len(self.keys) + right
        if (known := self.compatible.get(code)) is None:
            if len(self.compatible) > 2_000_000:
                self.compatible.clear()
            known = self.compatible[code] = self._apart(left, right)
        return known

    def _apart(self, a: int, b: int) -> bool:
        """Whether BPE keeps a token boundary between a and b: undo the merges on both sides, latest first, and look for
        a merge across the boundary that would have come before the merge just undone."""
        undone = len(self.keys)
        while True:
            across = self.merged.get((a, b))
            if across is not None and across < undone:
                return False
            if a > b:  # a was merged later: its right part touched the boundary before
                if a < 256:
                    return True
                undone, a = a, self.parts[a][1]
            else:
                if b < 256:
                    return True
                undone, b = b + 1, self.parts[b][0]

    def pretoken(self, piece: str) -> list[int]:
        text = piece.encode().decode("latin-1")
        n = len(text)
        longest = self.matcher.iter_long
        dead = bytearray(n + 1)
        out: list[int] = []
        at = 0
        if n:
            token = next(longest(text))[1]
        while at < n:
            while True:
                end = at + self.sizes[token]
                if not dead[end] and (not out or self.may_follow(out[-1], token)):
                    out.append(token)
                    at = end
                    if at < n:
                        token = next(longest(text, at))[1]
                    break
                less = self.prefix(token)
                if less is None:
                    dead[at] = 1
                    token = out.pop()
                    at -= self.sizes[token]
                    break
                token = less
        return [self.external[t] for t in out]

    def find(self, text: str) -> list[str]:
        """The pretokens. Where the two regex libraries know different versions of Unicode, the tokenizer's own decides."""
        if text.isascii():
            return self.find_ascii(text)
        for c in set(text):
            if (same := self.agreed.get(c)) is None:
                probe = f"a{c}1{c}!{c} {c}"
                same = self.agreed[c] = self.find_any(probe) == self.find_library(probe)
            if not same:
                return self.find_library(text)
        return self.find_any(text)

    def find_library(self, text: str) -> list[str]:
        return [text[a:b] for _, (a, b) in self.library.pre_tokenize_str(text)]

    def pieces(self, text: str) -> Iterator[str]:
        while len(text) > CUT:
            cut = self.cut_at.search(text, CUT)
            if cut is None:
                break
            yield text[: cut.start()]
            text = text[cut.start() :]
        yield text

    def encode(self, text: str) -> np.ndarray:
        out: list[bytes] = []
        look = self.cache.__getitem__
        spans = [(text, None)]
        if self.split is not None and any(s in text for s in self.special):
            spans, at = [], 0
            for m in self.split.finditer(text):
                spans.append((text[at : m.start()], m.group()))
                at = m.end()
            spans.append((text[at:], None))
        for plain, special in spans:
            for piece in self.pieces(plain):
                out.append(b"".join(map(look, self.find(piece))))
            if special is not None:
                out.append(array("I", [self.special[special]]).tobytes())
        return np.frombuffer(b"".join(out), np.uint32)

    def decode(self, ids: np.ndarray) -> str:
        return b"".join(x.tobytes() for x in self.spelled.render(ids)).decode("utf-8", "replace")


class Remembered(dict):
    """What a function gives for short strings. When full, the entries become the older half, and that half goes."""

    def __init__(self, compute, entries: int = CACHE_ENTRIES, length: int = CACHE_LENGTH) -> None:
        super().__init__()
        self.compute, self.entries, self.length, self.older = compute, entries, length, {}

    def __missing__(self, piece):
        value = self.older.get(piece)
        if value is None:
            value = self.compute(piece)
            if len(piece) > self.length:
                return value
        if len(self) >= self.entries:
            self.older = dict(self)
            self.clear()
        self[piece] = value
        return value


@functools.lru_cache(maxsize=2)
def load(path: str) -> PairEncoder:
    return PairEncoder(path)


def ids_digest(enc: PairEncoder, ids: np.ndarray) -> str:
    sha, last = hashlib.sha256(), b""
    for block in enc.decimal.render(ids):
        sha.update(last)
        last = block.tobytes()
    sha.update(last[:-1])
    return sha.hexdigest()


def decoded_digest(enc: PairEncoder, ids: np.ndarray) -> str:
    data = b"".join(x.tobytes() for x in enc.spelled.render(ids))
    try:
        data.decode()
    except UnicodeDecodeError:
        data = data.decode("utf-8", "replace").encode()
    return hashlib.sha256(data).hexdigest()


def encode(docs: DataFrame, text_col: str = "text", path: str | None = None, out: str = "ids", keep=None) -> DataFrame:
    """Rows with an array column of token ids."""
    path = path or default_path()

    def kernel():
        enc = load(path)
        return lambda texts, _: [pa.array([enc.encode(t).astype(np.int32) for t in texts], pa.list_(pa.int32()))]

    return append_columns(docs, text_col, kernel, [(out, T.ArrayType(T.IntegerType()))], keep)


def decode(rows: DataFrame, ids_col: str = "ids", path: str | None = None, out: str = "text", keep=None) -> DataFrame:
    """Rows with the text of their ids; null ids count as none."""
    path = path or default_path()
    kept = [c for c in (rows.columns if keep is None else keep) if c != out]
    src = rows.select(*dict.fromkeys([*kept, ids_col]))
    schema = T.StructType([src.schema[c] for c in kept] + [T.StructField(out, T.StringType())])

    def run(batches):
        enc = load(path)
        for b in batches:
            texts = [enc.decode(np.asarray(x or [], np.int64)) for x in b.column(b.schema.get_field_index(ids_col)).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index(c)) for c in kept] + [pa.array(texts, pa.string())], names=[*kept, out])

    return src.mapInArrow(run, schema)


def round_trip(docs: DataFrame, text_col: str = "text", path: str | None = None, keep=("doc_id",)) -> DataFrame:
    """Encode every whole text and decode it again: n_tokens, ids_sha256, decoded_sha256 beside the kept columns."""
    path = path or default_path()

    def kernel():
        enc = load(path)

        def work(texts, _):
            counts, a, b = [], [], []
            for text in texts:
                ids = enc.encode(text)
                counts.append(len(ids))
                a.append(ids_digest(enc, ids))
                b.append(decoded_digest(enc, ids))
            return [pa.array(counts, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())]

        return work

    fields = [("n_tokens", T.LongType()), ("ids_sha256", T.StringType()), ("decoded_sha256", T.StringType())]
    return append_columns(docs, text_col, kernel, fields, list(keep))
