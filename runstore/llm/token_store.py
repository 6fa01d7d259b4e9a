"""Operator 2: token-id files with Elias-Fano encoded document boundaries.

A *segment* is one byte string: a fixed header, the ids of consecutive
documents laid end to end (2 bytes each where the vocabulary allows, else 4),
and the documents' end offsets as an Elias-Fano sequence.  For n offsets below
u, every offset keeps its floor(log2(u/n)) low bits in a packed array, and its
high part as one set bit in a unary bit vector.  The segment also stores a
sampled select directory: the bit position of every 256th set bit, 4 bytes
each.  The i-th offset is found from there by a short scan of bit counts, so no
reader holds a table of 64-bit numbers.  About 2.2 + log2(u/n) bits per document.

Segments are rows of a Parquet table ordered by `(part, seq)`, which is the
ascending order of ids: Spark's committer makes the files, so a task that is
run again replaces its own and a lost executor leaves nothing half-written, on
any store.  `read_token_table` gives starts and lengths of all documents and
`read_documents` the ids of some, both by selects.  `export_files` writes the
same bytes as flat files.

Texts cross one range shuffle and are encoded behind it (compressed texts are
no larger than their ids, so encoding first would only add a copy).  Words are
found, made distinct and put together again in columns; only distinct words
that a worker has not met reach the library.

Nulls: a null text counts as empty; a null id sorts first.  Repeated ids are
kept (ordered by text).  Empty texts hold the end id alone.  Very long texts
are encoded a text at a time.  An empty table gives no segments and no rows.
Other columns of the input, whatever their names, are not read.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

MAGIC = b"RSEF0002"
HEADER = struct.Struct("<8sIIQQQQ")  # magic, id bytes, low bits, docs, tokens, low words, high words
SAMPLE = 256
#: A segment ends with the document that brings it over one of these.
SEGMENT_TOKENS, SEGMENT_DOCS = 1_000_000, 4096
#: Words a worker remembers with their ids (about 200 bytes each), in two generations.
CACHE_WORDS = 300_000
#: Longer words are not remembered.
LONG_WORD = 64
#: Bytes of text that are split into words at a time; a longer text is taken alone.
HELD_BYTES = 4 << 20


class EliasFano:
    """A non-decreasing sequence of integers in near-minimal space with select."""

    def __init__(self, low_bits: int, n: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray):
        self.low_bits, self.n, self.low, self.high, self.samples = low_bits, n, low, high, samples

    @classmethod
    def encode(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, dtype=np.uint64)
        n = len(values)
        if n == 0:
            return cls(0, 0, np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.uint32))
        upper = int(values[-1]) + 1
        low_bits = max(0, (upper // n).bit_length() - 1)
        if low_bits:
            shifts = np.arange(low_bits, dtype=np.uint64)
            bits = ((values[:, None] >> shifts) & np.uint64(1)).astype(np.uint8).ravel()
        else:
            bits = np.zeros(0, np.uint8)
        ones = (values >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        if ones[-1] >= 1 << 32:
            raise ValueError("too many values for one sequence")
        marks = np.zeros(int(ones[-1]) + 1, np.uint8)
        marks[ones] = 1
        return cls(low_bits, n, cls._words(bits), cls._words(marks), ones[::SAMPLE].astype(np.uint32))

    @staticmethod
    def _words(bits: np.ndarray) -> np.ndarray:
        bits = np.concatenate([bits, np.zeros(-len(bits) % 64, np.uint8)])
        return np.packbits(bits, bitorder="little").view(np.uint64)

    def select(self, at) -> np.ndarray | int:
        """The values at the given places (one, or an array of them).

        From each place's sampled bit position whole words are counted until the
        wanted bit is in the next one; then bits are dropped inside that word.
        """
        i = np.atleast_1d(np.asarray(at, np.int64))
        if len(i) and not (0 <= i.min() and i.max() < self.n):
            raise IndexError(at)
        begin = self.samples[i // SAMPLE].astype(np.int64)
        word, left = begin >> 6, i % SAMPLE
        bits = self.high[word] & (~np.uint64(0) << (begin & 63).astype(np.uint64))
        held = np.bitwise_count(bits).astype(np.int64)
        far = np.flatnonzero(held <= left)
        while len(far):
            left[far] -= held[far]
            word[far] += 1
            bits[far] = self.high[word[far]]
            held[far] = np.bitwise_count(bits[far])
            far = far[held[far] <= left[far]]
        drop = np.flatnonzero(left)
        while len(drop):
            bits[drop] &= bits[drop] - np.uint64(1)
            left[drop] -= 1
            drop = drop[left[drop] > 0]
        lowest = np.bitwise_count((bits & (~bits + np.uint64(1))) - np.uint64(1)).astype(np.int64)
        out = ((word * 64 + lowest - i).astype(np.uint64) << np.uint64(self.low_bits)) | self._lows(i)
        return int(out[0]) if np.ndim(at) == 0 else out

    def _lows(self, i: np.ndarray) -> np.ndarray:
        if not self.low_bits:
            return np.zeros(len(i), np.uint64)
        bit = i * self.low_bits
        word, off = bit >> 6, (bit & 63).astype(np.uint64)
        x = self.low[word] >> off
        over = np.flatnonzero(off + np.uint64(self.low_bits) > np.uint64(64))
        x[over] |= self.low[word[over] + 1] << (np.uint64(64) - off[over])
        return x & np.uint64((1 << self.low_bits) - 1)

    def decode(self) -> np.ndarray:
        """All values at once."""
        if not self.n:
            return np.zeros(0, np.uint64)
        at = np.flatnonzero(np.unpackbits(self.high.view(np.uint8), bitorder="little"))
        out = (at - np.arange(self.n)).astype(np.uint64) << np.uint64(self.low_bits)
        if self.low_bits:
            bits = np.unpackbits(self.low.view(np.uint8), bitorder="little")[: self.n * self.low_bits]
            out |= (bits.reshape(self.n, self.low_bits).astype(np.uint64) << np.arange(self.low_bits, dtype=np.uint64)).sum(1, dtype=np.uint64)
        return out


def pack(ids: np.ndarray, ends: np.ndarray, id_bytes: int) -> bytes:
    """One segment; ends[i]: number of ids up to the end of its i-th document."""
    ef = EliasFano.encode(ends)
    head = HEADER.pack(MAGIC, id_bytes, ef.low_bits, ef.n, len(ids), len(ef.low), len(ef.high))
    return b"".join((head, ef.low.tobytes(), ef.high.tobytes(), ef.samples.astype("<u4").tobytes(), ids.astype(f"<u{id_bytes}").tobytes()))


def unpack(segment: bytes) -> tuple[np.ndarray, EliasFano]:
    """ids (a view) and the document ends of a segment."""
    magic, id_bytes, low_bits, n, tokens, lows, highs = HEADER.unpack_from(segment)
    if magic != MAGIC:
        raise ValueError("not a token segment")
    at = HEADER.size
    low = np.frombuffer(segment, np.uint64, lows, at)
    high = np.frombuffer(segment, np.uint64, highs, at + 8 * lows)
    at += 8 * (lows + highs)
    samples = np.frombuffer(segment, "<u4", -(-n // SAMPLE), at)
    ids = np.frombuffer(segment, f"<u{id_bytes}", tokens, at + 4 * len(samples))
    return ids, EliasFano(low_bits, n, low, high, samples)


#: Letters that NFC leaves alone and Python lower-cases as the library does (ASCII, Latin-1), then marks.
_PLAIN = r"^(?P<w>[A-Za-zÀ-ÖØ-öø-ÿ]+)(?P<m>[!-/:-@\[-`{-~]*)$"
_SAFE = re.compile(r"[!-;=-~À-ÖØ-öø-ÿ]+")
#: The tokenizer's pre-tokens in a safe word in lower case.
_PIECES = re.compile(r"[a-zß-öø-ÿ]+|'(?:s|t|re|ve|m|ll|d)|[0-9]|[^a-zß-öø-ÿ0-9]+")


class WordEncoder:
    """ids of whole texts by the tokenizers library, each distinct word encoded once.

    Valid for tokenizers that drop white space: no token spans a blank, so a
    text's ids are those of its blank-separated words in turn.  Where
    `split_marks` holds (case is folded, and letters, digits and runs of marks
    are pre-tokens of their own), words of common characters are taken apart
    first, so that fewer distinct strings reach the library; all other words
    are the library's own to take apart.
    """

    def __init__(self, name: str, split_marks: bool):
        import os

        import public_tokenizers
        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tok = Tokenizer.from_file(public_tokenizers.path(name))
        self.id_bytes = 2 if self.tok.get_vocab_size(with_added_tokens=True) <= 1 << 16 else 4
        self.split_marks, self.known = split_marks, base.TwoGenerationCache(CACHE_WORDS)

    def _library(self, words: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype="<u4").tobytes() for e in self.tok.encode_batch_fast(words, add_special_tokens=False)]

    def _pieces(self, pieces: list[str]) -> list[bytes]:
        before, run = self.tok.pre_tokenizer.pre_tokenize_str, self.tok.model.tokenize
        out = []
        for p in pieces:
            ids = [t.id for t in run(p if p.isascii() else before(p)[0][0])]
            out.append(struct.pack(f"<{len(ids)}I", *ids))
        return out

    def _look_up(self, words: list[str], make: Callable[[list[str]], list[bytes]]) -> pa.Array:
        known = self.known.ensure([w for w in words if len(w) <= LONG_WORD], make)
        out = list(map(known.get, words))
        if None in out:
            late = [i for i, x in enumerate(out) if x is None]
            for i, x in zip(late, make([words[i] for i in late])):
                out[i] = x
        return pa.array(out, pa.large_binary())

    def _column(self, words: pa.Array, make: Callable[[list[str]], list[bytes]]) -> pa.Array:
        """ids of each word of a column, by its distinct words."""
        coded = words.dictionary_encode()
        return self._look_up(coded.dictionary.to_pylist(), make).take(coded.indices)

    def _others(self, words: list[str]) -> list[bytes]:
        """Words that are not letters and closing marks."""
        out: list = [None] * len(words)
        safe = [_PIECES.findall(w.lower()) if _SAFE.fullmatch(w) else None for w in words]
        found = self._column(pa.array([p for x in safe if x for p in x], pa.string()), self._pieces).to_pylist()
        at = 0
        for i, x in enumerate(safe):
            if x is not None:
                out[i] = b"".join(found[at : at + len(x)])
                at += len(x)
        odd = [i for i, x in enumerate(safe) if x is None]
        for i, ids in zip(odd, self._library([words[i] for i in odd])):
            out[i] = ids
        return out

    def _distinct(self, words: pa.Array) -> pa.Array:
        """ids of each of distinct words."""
        if not self.split_marks:
            return self._look_up(words.to_pylist(), self._library)
        cut = pc.extract_regex(words, _PLAIN)
        plain = cut.is_valid()
        cut = cut.drop_null()
        ids = pc.binary_join_element_wise(self._column(pc.utf8_lower(cut.field("w")), self._pieces), self._column(cut.field("m"), self._pieces), pa.scalar(b"", pa.large_binary()))
        rest = words.filter(pc.invert(plain)).to_pylist()
        if not rest:
            return ids
        place = np.empty(len(words), np.int64)
        mask = plain.to_numpy(zero_copy_only=False)
        place[mask], place[~mask] = np.arange(len(ids)), len(ids) + np.arange(len(rest))
        return pa.concat_arrays([ids, pa.array(self._others(rest), pa.large_binary())]).take(pa.array(place))

    def encode_column(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts in a row, number of ids of each text)."""
        words = pc.ascii_split_whitespace(texts)
        coded = words.flatten().dictionary_encode()
        ids = self._distinct(coded.dictionary)
        sizes = pc.binary_length(ids).to_numpy() // 4
        at = coded.indices.to_numpy()
        ends = np.concatenate([[0], np.cumsum(sizes[at])])
        cuts = words.offsets.to_numpy()
        # gather the words' ids as numbers: one index array of the batch's ids
        flat = np.frombuffer(ids.buffers()[2] or b"", "<u4")
        begin = np.frombuffer(ids.buffers()[1], np.int64)[ids.offset : ids.offset + len(ids) + 1][:-1] // 4
        n = sizes[at]
        where = np.repeat(begin[at] - ends[:-1], n) + np.arange(ends[-1])
        return flat[where], np.diff(ends[cuts - cuts[0]])

    def encode(self, text: str) -> bytes:
        """The text's ids as little-endian unsigned 32-bit integers."""
        return self.encode_column(pa.array([text]))[0].tobytes()


def encoder(name: str, split_marks: bool) -> WordEncoder:
    """This worker's encoder; workers outlive tasks, so words stay known."""
    return base.held(("words", name, split_marks), lambda: WordEncoder(name, split_marks))


SEGMENTS = "part int, seq int, base long, docs long, tokens long, first long, last long, doc_ids binary, null_ids binary, segment binary"


def write_token_table(docs: DataFrame, path: str, tokenizer: str = "word_bpe_49k.json", end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", split_marks: bool = True) -> None:
    """Encode every whole text and write the segments in ascending order of ids.

    One range shuffle of (id, text).  `base` counts the ids before a segment
    within its part; parts' totals are added on reading.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("d"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    rows = rows.repartitionByRange("d").sortWithinPartitions("d", "t")
    schema = pa.schema([("part", pa.int32()), *[(n, pa.int64()) for n in ("seq", "base", "docs", "tokens", "first", "last")], ("doc_ids", pa.binary()), ("null_ids", pa.binary()), ("segment", pa.binary())]).set(1, pa.field("seq", pa.int32()))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc, part = encoder(tokenizer, split_marks), TaskContext.get().partitionId()
        seq = before = held = 0
        ids: list[np.ndarray] = []
        lens: list[np.ndarray] = []
        keys: list[pa.Array] = []

        def flush() -> pa.RecordBatch:
            nonlocal seq, before, held
            flat, n, key = np.concatenate(ids), np.concatenate(lens), pa.concat_arrays(keys)
            width = 4 if len(flat) and int(flat.max()) >= 1 << 16 else enc.id_bytes
            ends = pc.min_max(key).as_py()
            out = pa.RecordBatch.from_pylist(
                [{
                    "part": part, "seq": seq, "base": before, "docs": len(n), "tokens": len(flat), "first": ends["min"], "last": ends["max"],
                    "doc_ids": key.fill_null(0).to_numpy().astype("<i8").tobytes(), "null_ids": key.is_null().to_numpy(zero_copy_only=False).astype("u1").tobytes(),
                    "segment": pack(flat, np.cumsum(n).astype(np.uint64), width),
                }],
                schema=schema,
            )
            seq, before, held = seq + 1, before + len(flat), 0
            ids.clear(), lens.clear(), keys.clear()
            return out

        for batch in batches:
            for a, b in base.slices(batch.column(1), HELD_BYTES):
                flat, n = enc.encode_column(batch.column(1).slice(a, b - a))
                # the end id behind each text
                flat, n = np.insert(flat, np.cumsum(n), end_id), n + 1
                cuts = np.cumsum(n)
                at = 0
                while at < len(n):  # documents that still fit, one at least
                    used = cuts[at - 1] if at else 0
                    room = int(np.searchsorted(cuts, used + SEGMENT_TOKENS - held, side="left")) + 1
                    to = min(len(n), room, at + SEGMENT_DOCS - sum(map(len, lens)))
                    ids.append(flat[used : cuts[to - 1]])
                    lens.append(n[at:to])
                    keys.append(batch.column(0).slice(a + at, to - at))
                    held, at = held + int(cuts[to - 1] - used), to
                    if held >= SEGMENT_TOKENS or sum(map(len, lens)) >= SEGMENT_DOCS:
                        yield flush()
        if lens:
            yield flush()

    rows.mapInArrow(encode, SEGMENTS).write.option("compression", "zstd").mode("overwrite").parquet(path)


def _bases(segments: DataFrame) -> dict[int, int]:
    """Number of ids before each part: one number a written partition reaches the driver."""
    bases, n = {}, 0
    for part, tokens in sorted((r["part"], r["n"]) for r in segments.groupBy("part").agg(F.sum("tokens").alias("n")).collect()):
        bases[part] = n
        n += tokens
    return bases


def _spans(ef: EliasFano, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of the documents at the given places of a segment, by selects."""
    ends = ef.select(at).astype(np.int64)
    starts = np.zeros(len(at), np.int64)
    later = np.flatnonzero(at > 0)
    starts[later] = ef.select(at[later] - 1)
    return starts, ends


def read_token_table(spark: SparkSession, path: str) -> DataFrame:
    """Documents of a token table: doc_id, start, n_tokens, ids_crc32, in no set order."""
    segments = spark.read.schema(SEGMENTS).parquet(path)
    bases = _bases(segments)

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids, ef = unpack(row["segment"])
                starts, ends = _spans(ef, np.arange(ef.n))
                wide = ids.astype("<u4")
                crc = [zlib.crc32(wide[a:b]) for a, b in zip(starts.tolist(), ends.tolist())]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.frombuffer(row["doc_ids"], "<i8"), mask=np.frombuffer(row["null_ids"], "u1").astype(bool)),
                        pa.array(starts + (bases[row["part"]] + row["base"])),
                        pa.array(ends - starts),
                        pa.array(crc, pa.int64()),
                    ],
                    names=["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    return segments.select("part", "base", "doc_ids", "null_ids", "segment").mapInArrow(decode, "doc_id long, start long, n_tokens long, ids_crc32 long")


def read_documents(spark: SparkSession, path: str, wanted: list[int]) -> DataFrame:
    """Rows (doc_id, ids) of the documents of the given ids; only segments whose range holds one are decoded."""
    near = F.exists(F.array(*[F.lit(int(w)) for w in wanted]).cast("array<long>"), lambda w: w.between(F.col("first"), F.col("last")))
    segments = spark.read.schema(SEGMENTS).parquet(path).where(near)
    wants = np.array(sorted(set(wanted)), np.int64)

    def take(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                keys = np.frombuffer(row["doc_ids"], "<i8")
                at = np.flatnonzero(np.isin(keys, wants) & (np.frombuffer(row["null_ids"], "u1") == 0))
                if len(at):
                    ids, ef = unpack(row["segment"])
                    found = [ids[a:b].astype(np.int64) for a, b in zip(*_spans(ef, at))]
                    yield pa.RecordBatch.from_arrays([pa.array(keys[at]), pa.array(found, pa.list_(pa.int64()))], names=["doc_id", "ids"])

    return segments.select("doc_ids", "null_ids", "segment").mapInArrow(take, "doc_id long, ids array<long>")


def export_files(spark: SparkSession, path: str, folder: str) -> list[str]:
    """Write a token table as flat files `part-seq.tok` below a mounted folder, one segment at a time."""
    import os

    os.makedirs(folder, exist_ok=True)
    names = []
    for row in spark.read.schema(SEGMENTS).parquet(path).select("part", "seq", "segment").orderBy("part", "seq").toLocalIterator():
        names.append(os.path.join(folder, f"{row['part']:06d}-{row['seq']:06d}.tok"))
        with open(names[-1] + ".tmp", "wb") as f:
            f.write(row["segment"])
        os.replace(names[-1] + ".tmp", names[-1])
    return names


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = base.scratch(spark, "tokens")
    write_token_table(base.table(spark, sf_dir, "documents"), path)
    return read_token_table(spark, path)
