"""Token ids and their binary files.

Texts are encoded with a public byte-level BPE file by the tokenizers library. That encoder never looks across a single
space that has another sign than white space beside it, so a text falls into words (each with the space before it), and
each worker keeps the ids of the words that it has met and asks the library for new ones alone. A text
with white space other than spaces and line ends, runs of spaces, a special token's string or letters beyond Latin goes
to the library whole. The ids are the same either way. What is kept is bounded in number and length.

File format, one shard for each range of document ids: records framed as length (u64), masked CRC-32C of the length,
payload, masked CRC-32C of the payload, all little-endian. A payload is the document's id (i64, least value: null), the
bytes of one id (u8: 2 or 4), and the ids. Beside each shard lies an index: for each record document id (i64), offset
(u64) and number of ids (u64), for reads in any order. Both are written under a name of the attempt and then moved, so
a repeated task leaves the same files. Null texts are empty: such a document has the end id alone.
"""

from __future__ import annotations

import os
import re
import struct
import uuid
import zlib
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import begins, scratch, tidied

END, NO_ID = 2, -(2**63)
#: Characters of which only the space and the line end are white space.
_PLAIN = re.compile(r"[\n\x20-\x7eÀ-ÖØ-öø-ɏ]*")
#: White space, and signs that the pattern above leaves out, of ASCII texts.
_ODD = ("\t", "\r", "\x0b", "\x0c", "\x1c", "\x1d", "\x1e", "\x1f", "\0")
#: Words that a worker keeps in each of two generations (some 150 bytes each), and the longest that is kept.
WORDS, _LONG = 100_000, 48
#: The sign by which byte-level vocabularies write a space.
SPACE = "Ġ"
#: Signs that often follow a word.
_SIGNS = ".,;:!?)*$\""
_HEAD, _INDEX = struct.Struct("<QI"), np.dtype([("doc", "<i8"), ("at", "<u8"), ("n", "<u8")])


@lru_cache(1)
def _byte_signs() -> dict[int, str]:
    """The sign by which byte-level vocabularies write each byte: printable ones themselves, the rest from 256 on."""
    kept = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in kept]
    return {b: chr(b) for b in kept} | {b: chr(256 + i) for i, b in enumerate(rest)}


def _by_words(text: str) -> bool:
    """Whether the encoder cuts the text at each of its spaces, whatever stands around them."""
    if "  " in text or "\n \n" in text or text[-1:] == " ":
        return False
    return not any(c in text for c in _ODD) if text.isascii() else _PLAIN.fullmatch(text) is not None


class _Known(dict):
    """Ids of words in two generations: when the new one is full it becomes the old one, and what is met again moves
    back, so frequent words stay and memory is bounded. Words that neither has are learnt, and kept unless long."""

    def __init__(self, learn, most: int):
        super().__init__()
        self.old: dict[str, bytes] = {}
        self.learn, self.most = learn, most

    def __missing__(self, word: str) -> bytes:
        found = self.old.get(word)
        if found is None:
            found = self.learn(word) if word.isalpha() else self._parts(word)
        if len(word) <= _LONG:
            self[word] = found
        return found

    def _parts(self, word: str) -> bytes:
        """Of a word that is not known: a single line end inside and the signs after a letter or digit stand alone."""
        head, end, rest = word.partition("\n")
        if end and head.strip("\0") and rest[:1] not in ("", "\n"):
            return self[head] + self["\0\n"] + self["\0" + rest]
        core = word.rstrip(_SIGNS)
        if core != word and core[-1:].isalnum():
            return self[core] + self["\0" + word[len(core) :]]
        return self.learn(word)

    def turn(self) -> None:
        if len(self) > self.most:
            self.old = dict(self)
            self.clear()


class Encoder:
    """Ids of texts as bytes, two or four to an id."""

    def __init__(self, path: str, words: int = WORDS):
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        before = self.tokenizer.pre_tokenizer
        self.by_word = self.tokenizer.normalizer is None and isinstance(before, pre_tokenizers.ByteLevel) and before.use_regex and not before.add_prefix_space
        self.kind = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.cut, self.code = self.tokenizer.model.tokenize, "H" if self.kind.itemsize == 2 else "I"
        self.known = _Known(self.word, words)

    def library(self, text: str) -> bytes:
        return array(self.code, self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def word(self, word: str) -> bytes:
        """Ids of a word with the space before it, which is none where it starts with the null sign."""
        bare = word[:1] == "\0"
        letters = word[1:] if bare else word
        if letters.isalpha():  # one piece; byte-level vocabularies write ASCII letters as they are
            written = letters if letters.isascii() else letters.encode().decode("latin-1").translate(_byte_signs())
            return array(self.code, [t.id for t in self.cut(written if bare else SPACE + written)]).tobytes()
        return self.library(letters if bare else " " + word)

    def encode(self, texts: list[str]) -> list[bytes]:
        out = []
        for t in texts:
            self.known.turn()
            if not self.by_word or not _by_words(t) or any(s in t for s in self.special):
                out.append(self.library(t))
            else:
                first, *words = t.split(" ")
                out.append(b"".join(map(self.known.__getitem__, ["\0" + first, *words])))  # the first has no space before it
        return out


@lru_cache(1)
def _encoder(path: str, words: int) -> Encoder:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
    return Encoder(path, words)


def encoder(path: str, words: int = WORDS) -> Encoder:
    """The worker's encoder, kept from task to task until another operator's work begins there."""
    begins("tokens", _encoder.cache_clear)
    return _encoder(path, words)


def some_texts(col: pa.Array, chars: int = 1 << 18):
    """(first row, texts) for runs of rows of about so many characters; null is empty."""
    lo, size, held = 0, 0, []
    for t in col:
        t = t.as_py() or ""
        held.append(t)
        size += len(t)
        if size >= chars:
            yield lo, held
            lo, size, held = lo + len(held), 0, []
    if held:
        yield lo, held


_STEP = 1024


@lru_cache(1)
def _tables(size: int = _STEP) -> np.ndarray:
    """CRC-32C of one byte with so many zero bytes after it."""
    one = np.arange(256, dtype=np.uint32)
    for _ in range(8):
        one = np.where(one & 1, (one >> 1) ^ np.uint32(0x82F63B78), one >> 1)
    out = np.zeros((size, 256), np.uint32)
    out[0] = one
    for k in range(1, size):
        out[k] = (out[k - 1] >> 8) ^ one[out[k - 1] & 255]
    return out


@lru_cache(1)
def _shifts() -> list[list[int]]:
    """How a state goes on over a whole step of zero bytes, by each of its bytes."""
    return [_tables()[_STEP - 1 - i].tolist() for i in range(4)]


def crc32c_each(parts: list[bytes]) -> list[int]:
    """The CRC of each part. It is linear: each byte of a step adds what it and its distance to the step's end give, for
    all parts at once, and only the states between steps are carried on one by one."""
    table = _tables()
    flat, (s0, s1, s2, s3) = table.ravel(), _shifts()
    sizes = np.array([len(p) for p in parts], np.int64)
    data = np.frombuffer(b"".join(parts), np.uint8)
    starts = np.cumsum(sizes) - sizes
    steps = -(-sizes // _STEP)
    first = np.repeat(starts, steps) + (np.arange(steps.sum()) - np.repeat(np.cumsum(steps) - steps, steps)) * _STEP
    last = np.minimum(first + _STEP, np.repeat(starts + sizes, steps))
    far = np.repeat((last - 1).astype(np.int32), last - first) - np.arange(len(data), dtype=np.int32)
    sums = np.bitwise_xor.reduceat(flat[(far << 8) + data], first).tolist() if len(first) else []
    out, at = [], 0
    for size, n in zip(sizes.tolist(), steps.tolist(), strict=True):
        state = 0xFFFFFFFF
        for i in range(n):
            length = _STEP if i + 1 < n else size - i * _STEP
            if length == _STEP:
                state = s0[state & 255] ^ s1[state >> 8 & 255] ^ s2[state >> 16 & 255] ^ s3[state >> 24]
            else:
                moved = state >> 8 * length if length < 4 else 0
                for b in range(min(4, length)):
                    moved ^= int(table[length - 1 - b, state >> 8 * b & 255])
                state = moved
            state ^= sums[at]
            at += 1
        out.append(state ^ 0xFFFFFFFF)
    return out


def crc32c(held: bytes) -> int:
    return crc32c_each([held])[0]


def masked(crc: int) -> int:
    return (((crc >> 15) | (crc << 17)) + 0xA282EAD8) & 0xFFFFFFFF


def framed(payloads: list[bytes]) -> list[bytes]:
    """Each payload as a record."""
    sizes = [struct.pack("<Q", len(p)) for p in payloads]
    marks = crc32c_each(sizes + payloads)
    return [b"".join((s, struct.pack("<I", masked(a)), p, struct.pack("<I", masked(b)))) for s, p, a, b in zip(sizes, payloads, marks[: len(sizes)], marks[len(sizes) :], strict=True)]


def records(held, at: int = 0, verify: bool = True):
    """(offset, payload) of each record of a file's bytes; raises where a checksum is wrong or the file ends early."""
    n = len(held)
    while at < n:
        if at + 12 > n:
            raise ValueError(f"cut record at {at}")
        size, mark = _HEAD.unpack_from(held, at)
        payload = held[at + 12 : at + 12 + size]
        if len(payload) < size or at + 16 + size > n:
            raise ValueError(f"cut record at {at}")
        if verify:
            a, b = crc32c_each([bytes(held[at : at + 8]), bytes(payload)])
            if masked(a) != mark or masked(b) != struct.unpack_from("<I", held, at + 12 + size)[0]:
                raise ValueError(f"wrong checksum at {at}")
        yield at, payload
        at += 16 + size


def unpack(payload: bytes) -> tuple[int | None, np.ndarray]:
    """(document id, ids) of a payload."""
    doc, width = struct.unpack_from("<qB", payload)
    return None if doc == NO_ID else doc, np.frombuffer(payload, "<u2" if width == 2 else "<u4", offset=9)


def read_at(path: str, rows: np.ndarray) -> list[tuple[int | None, np.ndarray]]:
    """Documents of one shard by their place in its index, in any order."""
    fs, at = pafs.FileSystem.from_uri(path)
    with fs.open_input_file(at + ".idx") as f:
        index = np.frombuffer(f.read(), _INDEX)
    out = []
    with fs.open_input_file(at) as f:
        for r in rows:
            offset = int(index["at"][r])
            f.seek(offset)
            size = struct.unpack("<Q", f.read(8))[0]
            f.seek(offset)
            out.append(unpack(next(records(f.read(16 + size)))[1]))
    return out


def _writer(tokenizer: str, folder: str, end: int | None, words: int):
    def go(batches):
        shard = TaskContext.get().partitionId()
        enc, name = encoder(tokenizer, words), f"shard-{shard:06d}.rec"
        fs, top = pafs.FileSystem.from_uri(folder)
        fs.create_dir(top, recursive=True)
        own = f"{top}/.{name}-{uuid.uuid4().hex}"
        docs = total = at = 0
        rows = []
        tail = b"" if end is None else np.array([end], enc.kind).tobytes()
        width = bytes([enc.kind.itemsize])
        out = None
        for batch in batches:
            ids = batch.column(0).to_pylist()
            for lo, texts in some_texts(batch.column(1)):
                own_ids = [NO_ID if doc is None else doc for doc in ids[lo : lo + len(texts)]]
                coded = enc.encode(texts)
                if out is None:
                    out = fs.open_output_stream(own)
                whole = framed([struct.pack("<q", doc) + width + held + tail for doc, held in zip(own_ids, coded, strict=True)])
                out.write(b"".join(whole))
                for doc, made in zip(own_ids, whole, strict=True):
                    n = (len(made) - 25) // enc.kind.itemsize  # without the frame, the document's id and the width
                    rows.append((doc, at, n))
                    at, docs, total = at + len(made), docs + 1, total + n
        if out is not None:
            out.close()
            with fs.open_output_stream(own + ".idx") as f:
                f.write(np.array(rows, _INDEX).tobytes())
            fs.move(own + ".idx", f"{top}/{name}.idx")
            fs.move(own, f"{top}/{name}")
            yield pa.RecordBatch.from_pydict({"shard": [shard], "path": [f"{folder}/{name}"], "docs": [docs], "ids": [total]}, pa.schema([("shard", pa.int32()), ("path", pa.string()), ("docs", pa.int64()), ("ids", pa.int64())]))

    return go


def write_ids(docs: DataFrame, tokenizer: str, folder: str | None = None, end: int | None = END, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS) -> list[dict]:
    """Write all documents' ids, ascending by document id over the shards in order, and return the shards: path, docs,
    ids and start (ids in the shards before). folder: a URI that every executor reaches. Rows without an id come first.
    Rows that repeat an id are in the order of their text's hash and then text, and may lie in several shards, so the
    order is the same whatever the partitions, and one id with many rows is not one task's."""
    folder = folder or f"{scratch(docs.sparkSession)}/ids-{uuid.uuid4().hex}"
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("mark", F.xxhash64("text"))
    dealt = rows.repartitionByRange("doc_id", "mark").sortWithinPartitions("doc_id", "mark", "text").select("doc_id", "text")
    made = sorted(dealt.mapInArrow(tidied(_writer(tokenizer, folder, end, words)), "shard int, path string, docs bigint, ids bigint").collect(), key=lambda r: r["shard"])
    start, out = 0, []
    for r in made:
        out.append({"path": r["path"], "docs": r["docs"], "ids": r["ids"], "start": start})
        start += r["ids"]
    return out


def read_ids(spark, shards: list[dict]) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) for every document of the shards, from their files."""

    def work(batches):
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                fs, at = pafs.FileSystem.from_uri(path)
                rows = []
                with fs.open_input_stream(at, buffer_size=1 << 20) as f:
                    for payload in streamed(f):
                        doc, ids = unpack(payload)
                        rows.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                        start += len(ids)
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    kind = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint"
    if not shards:
        return spark.createDataFrame([], kind)
    held = spark.createDataFrame([(s["path"], s["start"]) for s in shards], "path string, start bigint")
    return held.repartition(len(shards)).mapInArrow(work, kind)


def streamed(f, hold: int = 1 << 20):
    """Payloads of an open shard, checked, some megabyte of records in memory at a time."""
    done = False
    while not done:
        heads, payloads, marks, size = [], [], [], 0
        while size < hold:
            head = f.read(12)
            if not head:
                done = True
                break
            n = struct.unpack_from("<Q", head)[0] if len(head) == 12 else 0
            body = f.read(n + 4)
            if len(head) < 12 or len(body) < n + 4:
                raise ValueError("cut record")
            heads.append(head[:8])
            payloads.append(body[:n])
            marks.append((struct.unpack_from("<I", head, 8)[0], struct.unpack_from("<I", body, n)[0]))
            size += n
        found = [masked(c) for c in crc32c_each(heads + payloads)]
        if any((found[i], found[len(heads) + i]) != m for i, m in enumerate(marks)):
            raise ValueError("wrong checksum")
        yield from payloads


def _lengths(tokenizer: str, end: int | None, words: int = WORDS):
    def go(batches):
        enc = encoder(tokenizer, words)
        for batch in batches:
            sizes = [len(h) // enc.kind.itemsize + (end is not None) for _, texts in some_texts(batch.column(1)) for h in enc.encode(texts)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64())], names=["doc_id", "n_tokens"])

    return go


def token_counts(docs: DataFrame, tokenizer: str, end: int | None = END, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS) -> DataFrame:
    """(doc_id, n_tokens) for every row, the end id counted. words: as many a worker keeps (see WORDS)."""
    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidied(_lengths(tokenizer, end, words)), "doc_id bigint, n_tokens bigint")
