"""Harmonic packing of tokenised documents into fixed-length sequences.

A piece of length l is in class j if C/(j+1) < l <= C/j: j such pieces fill a sequence.  Pieces
are cut so that they nearly reach their class's bound (full sequences first, then bounds of
falling size), and what is left under C/64 goes to a tail class of short pieces.  A class's
sequences take a fixed number of pieces, so the sequence of the g-th piece is g // j: workers
number their pieces alone, and one summary of counts by class and bucket shifts the numbers.
Texts are tokenised in one narrow pass; only piece records move.

Null texts are empty and hold the end id alone, so they are one piece of length 1.  Repeated
rows are packed each for itself; null ids and extra columns stay as they are.  Very long texts
are cut into many pieces.  An empty table gives no sequences.
"""

from __future__ import annotations

import array
import itertools
import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import SPACE, cut, slices, spans, table, utf8

CAPACITY, CLASSES, END_ID, FILL, BUCKETS = 4096, 64, 2, 0.97, 1024


def byte_letters() -> list[str]:
    """The character that stands for each byte in a byte-level vocabulary: printable Latin-1 bytes
    stand for themselves, the others take the characters from 256 on, in order."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    odd = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(odd)) for b in range(256)]


class Memory:
    """What was learned about chunks, in two generations: when the young one holds `limit` bytes it
    becomes the old one, and what is met again moves back."""

    def __init__(self, limit: int):
        self.limit, self.held = limit, 0
        self.young: dict = {}
        self.old: dict = {}

    def put(self, key, value: bytes) -> None:
        self.young[key] = value
        self.held += len(key) + len(value) + 180
        if self.held > self.limit:
            self.young, self.old, self.held = {}, self.young, 0

    def get(self, key) -> bytes | None:
        value = self.young.get(key)
        if value is None and (value := self.old.get(key)) is not None:
            self.put(key, value)
        return value


#: Byte kinds: 1 letters (ASCII, and what U+00C0 to U+024F are made of), 2 digits, 3 marks, 0 others.
_KIND = np.zeros(256, np.uint8)
_KIND[33:127] = 3
_KIND[[*range(65, 91), *range(97, 123), *range(0x80, 0xC0), *range(0xC3, 0xCA)]] = 1
_KIND[48:58] = 2
_LOWERED = np.arange(256, dtype=np.uint8)
_LOWERED[65:91] += 32


class Ids:
    """Token ids of a batch of texts.

    Texts fall into units: the runs of letters, single digits and runs of marks that the
    tokenizer's pattern gives, in lower case, or a whole chunk between ASCII spaces where that is
    not plain to see (apostrophes, signs beyond U+024F, the file's own added tokens).  One
    dictionary encoding numbers a batch's units, so Python sees each different unit of a batch
    once, and the ids of all texts are one gather.  A unit's ids come from the tokenizer's
    model, or for a chunk from the whole tokenizer, and are remembered for the life of the
    worker, in a bounded number of bytes.

    That needs a file that composes, joins white space, lowers case, splits by a pattern of
    this kind and maps bytes to letters; with other files whole texts go to the tokenizer."""

    STEPS = ("NFC", "Replace", "Lowercase")
    PATTERN = "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"

    def __init__(self, path: str, limit: int = 64 << 20):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            form = json.load(f)
        steps = (form.get("pre_tokenizer") or {}).get("pretokenizers") or []
        added = [t["content"].encode() for t in form["added_tokens"]]
        self.by_unit = (
            tuple(x["type"] for x in (form.get("normalizer") or {}).get("normalizers", [])) == self.STEPS
            and [x["type"] for x in steps] == ["Split", "ByteLevel"]
            and (steps[0]["pattern"].get("Regex"), steps[0]["behavior"], steps[0]["invert"]) == (self.PATTERN, "Removed", True)
            and not (steps[1]["add_prefix_space"] or steps[1]["use_regex"] or form.get("post_processor"))
            and all(len(t) > 1 for t in added)
        )
        # two bytes that only a whole chunk may have: signs among the letters, a letter that lower case takes apart, added tokens
        self.twos = sorted({b"\xc3\x97", b"\xc3\xb7", b"\xc4\xb0", *(t[:2] for t in added)})
        self.odd = re.compile(b"|".join([rb"[\x00-\x20\x27\x7f\xc2\xca-\xff]", *map(re.escape, self.twos)])).search
        self.letters = dict(enumerate(byte_letters()))
        self.units = Memory(limit)

    def _whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _unit(self, unit: bytes) -> bytes:
        ids = self.units.get(unit)
        if ids is None:
            if self.odd(unit):
                ids = self._whole(unit.decode())
            else:
                own = unit.decode() if unit.isascii() else unit.decode().lower().encode().decode("latin-1").translate(self.letters)
                ids = array.array("I", [t.id for t in self.tokenizer.model.tokenize(own)]).tobytes()
            self.units.put(unit, ids)
        return ids

    def cut(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The units' bytes end to end, where each begins there (and the end), and each text's first unit."""
        starts, ends, _ = spans(data, offsets)
        kind = _KIND[data]
        after = np.append(data[1:], np.uint8(32))
        after[offsets[offsets > 0] - 1] = 32  # a text's last byte has none after it
        strange = (kind == 0) & ~SPACE[data] | (data == 39)
        for a, b in self.twos:
            strange |= (data == a) & (after == b)
        run = np.concatenate([[0], np.cumsum(strange, dtype=np.int64)])
        whole = run[ends] > run[starts]
        inside = np.zeros(len(data) + 1, np.int8)  # in a chunk that stays whole
        inside[starts[whole]] = 1
        inside[ends[whole]] -= 1
        inside = np.cumsum(inside[:-1], dtype=np.int8).astype(bool)
        first = np.zeros(len(data), bool)
        first[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == 2)
        first &= ~inside & ~SPACE[data]
        first[starts] = True
        ink = ~SPACE[data]
        place = np.concatenate([[0], np.cumsum(ink, dtype=np.int64)])
        at = np.flatnonzero(first)
        return np.where(inside, data, _LOWERED[data])[ink], np.append(place[at], place[-1]), np.searchsorted(at, offsets)

    def __call__(self, column: pa.Array) -> Iterator[bytes]:
        """The ids of each text of a string column, little-endian, 32 bits each."""
        if not self.by_unit:
            yield from (self._whole(t.as_py() or "") for t in column)
            return
        ink, at, first = self.cut(*utf8(column))
        coded = pa.Array.from_buffers(pa.large_binary(), len(at) - 1, [None, pa.py_buffer(at), pa.py_buffer(ink)]).dictionary_encode()
        number = coded.indices.to_numpy()
        known = list(map(self._unit, coded.dictionary.to_pylist()))
        size = np.fromiter(map(len, known), np.int64, len(known)) // 4
        ids, begins = np.frombuffer(b"".join(known), "<u4"), np.cumsum(size) - size
        many = size[number]
        upto = np.concatenate([[0], np.cumsum(many)])
        for a, b in itertools.pairwise(first.tolist()):
            n = number[a:b]
            yield ids[np.repeat(begins[n] - upto[a:b], many[a:b]) + np.arange(upto[a], upto[b])].tobytes()


_IDS: dict[str, Ids] = {}


def pieces(n: int, capacity: int = CAPACITY, classes: int = CLASSES, fill: float = FILL) -> Iterator[tuple[int, int]]:
    """(length, class) of the pieces of n tokens; class 0 is the tail."""
    least = capacity // classes
    while n >= least:
        j = max(1, capacity // n)
        bound = capacity // j
        if n < fill * bound:
            j += 1
            bound = capacity // j
        take = min(n, bound)
        yield take, j
        n -= take
    if n:
        yield n, 0


def _piece_rows(docs: DataFrame, path: str, keep: list[str], with_ids: bool, end_id: int, capacity: int) -> DataFrame:
    schema = docs.select(*keep).schema
    for name, kind in (("start", "long"), ("length", "long"), ("ids_crc32", "long"), ("doc_tokens", "long"), ("class", "integer"), *((("ids", "binary"),) if with_ids else ())):
        schema = schema.add(name, kind)
    tail = np.array([end_id], "<u4").tobytes()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        ids = _IDS.get(path) or _IDS.setdefault(path, Ids(path))
        for b in slices(batches, "_text", 2 << 20):
            at, start, length, crc, total, kind, raw = [], [], [], [], [], [], []
            for i, own in enumerate(ids(b.column("_text"))):
                own = memoryview(own + tail)
                x, n = 0, len(own) // 4
                for size, j in pieces(n, capacity):
                    part = own[4 * x : 4 * (x + size)]
                    at.append(i), start.append(x), length.append(size), crc.append(zlib.crc32(part)), total.append(n), kind.append(j)
                    if with_ids:
                        raw.append(bytes(part))
                    x += size
            kept = [b.column(k).take(pa.array(at, pa.int64())) for k in range(len(keep))]
            made = [pa.array(v, pa.int64()) for v in (start, length, crc, total)] + [pa.array(kind, pa.int32())] + ([pa.array(raw, pa.binary())] if with_ids else [])
            yield pa.RecordBatch.from_arrays([*kept, *made], names=schema.names)

    return docs.select(*keep, F.col("text").alias("_text")).mapInArrow(rows, schema)


def pack(docs: DataFrame, path: str, keep: list[str] | None = None, with_ids: bool = False, end_id: int = END_ID, capacity: int = CAPACITY) -> DataFrame:
    """One row for each piece: `keep` columns (doc_id), start, length, ids_crc32, doc_tokens,
    sequence_id and offset; `ids` (32-bit little-endian) too if asked."""
    keep = keep or ["doc_id"]
    rows = cut(_piece_rows(docs, path, keep, with_ids, end_id, capacity))  # tokenised once
    rows = rows.withColumn("_b", F.pmod(F.xxhash64(*keep, "start", "ids_crc32"), F.lit(BUCKETS)))
    # the tail class is measured in tokens, the others in pieces
    rows = rows.withColumn("_unit", F.when(F.col("class") == 0, F.col("length")).otherwise(F.lit(1)).cast("long"))
    sums = rows.groupBy("class", "_b").agg(F.sum("_unit").alias("n"))
    ahead = Window.partitionBy("class").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("class", "_b", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("_ahead"))
    inside = Window.partitionBy("class", "_b").orderBy(*keep, "start", "ids_crc32", "doc_tokens").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.join(starts, ["class", "_b"]).withColumn("_g", F.col("_ahead") + F.coalesce(F.sum("_unit").over(inside), F.lit(0)))
    # a tail sequence takes the pieces that begin inside its span, which leaves room for the last
    span = capacity - (capacity // CLASSES - 1) + 1
    number = F.expr(f"CASE WHEN class = 0 THEN _g DIV {span} ELSE _g DIV class END")
    rows = rows.withColumn("sequence_id", F.col("class").cast("long") * F.lit(1 << 40) + number)
    place = Window.partitionBy("sequence_id").orderBy("_g").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("offset", F.coalesce(F.sum("length").over(place), F.lit(0)))
    return rows.select(*keep, "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", *(["ids"] if with_ids else []))


def sequences(packed: DataFrame, pad_id: int = 0, capacity: int = CAPACITY) -> DataFrame:
    """sequence_id, n_tokens, input_ids (padded to `capacity` unless the tokens are a power of two
    in number) of what `pack(with_ids=True)` gives."""
    whole = packed.groupBy("sequence_id").agg(F.sum("length").alias("n_tokens"), F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("parts"))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for parts in b.column("parts").to_pylist():
                ids = np.frombuffer(b"".join(p["ids"] for p in parts), "<u4").astype(np.int32)
                out.append(ids if len(ids) & (len(ids) - 1) == 0 else np.pad(ids, (0, capacity - len(ids)), constant_values=pad_id))
            yield pa.RecordBatch.from_arrays([b.column("sequence_id"), b.column("n_tokens"), pa.array(out, pa.list_(pa.int32()))], ["sequence_id", "n_tokens", "input_ids"])

    return whole.mapInArrow(rows, "sequence_id long, n_tokens long, input_ids array<int>")


def padding(packed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """One row: n_sequences, n_tokens and the padding they need."""
    s = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.expr("n & (n - 1)") == 0, 0).otherwise(capacity - F.col("n"))
    return s.agg(F.count("*").alias("n_sequences"), F.sum("n").alias("n_tokens"), F.sum(pad).alias("n_padding"))


def public_vocabulary() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("word_bpe_49k.json"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents").select("doc_id", "text"), public_vocabulary())


QUERIES = {"op7_packing": op7_packing}
ORACLES: dict[str, str] = {}
