"""Operator 6: documents scored by cross-entropy difference of two n-gram models.

A target model (documents of the target set) and a background model (all
documents) are bigram models of the same kind over one shared vocabulary: the
most frequent words of the background (ties by spelling), all others being one
unknown word.  A word's probability after another is
`weight * c(v, w) / c(v) + (1 - weight) * (c(w) + 1) / (N + words)`, and the
last term alone where v was never seen; a document starts after a start mark.
A document's score is its loss per token under the target model less that
under the background model: the lower, the more like the target.

Words are runs between ASCII white space, lower-cased in ASCII.  The word
counts, bigram counts and scores are taken over all documents and whole texts;
only the vocabulary (`words` entries) and the bigram tables (at most words^2
entries) reach the driver and are broadcast, whatever the corpus' size.

`score_whole` is the same model over every word of the background (the unknown
word stays, never counted), so nothing is lost to a cut vocabulary.  Words are
64-bit hashes, bigrams 72-bit ones.  The documents are dealt into pieces by a
hash of id and text.  A piece counts its own bigrams and words and sends them,
sorted by hash, in one packed row to each range of hashes; a range sums what
came and sends each piece the totals in the order in which the keys came, so
keys travel once and no row is made of a bigram.  The piece counts again, puts
the totals beside its keys and sums the losses of its documents.  A bigram or
word, however frequent, is one key of a piece, so none makes a task large.
Only totals reach the driver, and nothing that is counted is broadcast.

A null text, or one without words, has 0 tokens and null losses and score.
Target ids that are null or not in the documents count for nothing; repeated
ids count once per document row.  An empty target set leaves the target model
uniform.  Very long texts make their piece as much longer.  An empty table
gives no rows.
Other columns, whatever their names, are not read.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

WORDS, WEIGHT = 1024, 0.7
#: Tokens counted before their sums are handed on, and bytes of text whose words are found at a time.
_HELD, _HELD_BYTES = 1_000_000, 2 << 20
#: Bytes of text of a piece whose counts are in hand together, about.
_HOT = 4 << 20
#: Bytes of text for each range of hashes, and for each of the first `_RANGES`, about.
_RANGE_BYTES, _FIRST_BYTES, _RANGES = 16 << 20, 4 << 20, 64
#: Stands before the first word.
_START = np.int64(0x51A27)
_STEP = np.uint64(0x9E3779B97F4A7C15)


def tokens(text: str | None) -> list[bytes]:
    return (text or "").encode().lower().split()


def vocabulary(texts: DataFrame, words: int) -> list[bytes]:
    """The `words` - 1 most frequent words of a one-column frame of texts."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter = Counter()

        def done() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(list(found), pa.binary()), pa.array(list(found.values()), pa.int64())], names=["w", "n"])
            found.clear()
            return out

        for batch in batches:
            for text in batch.column(0):
                found.update(tokens(text.as_py()))
                if len(found) > _HELD // 4:
                    yield done()
        yield done()

    counts = texts.mapInArrow(count, "w binary, n long").groupBy("w").agg(F.sum("n").alias("n"))
    return [bytes(r["w"]) for r in counts.orderBy(F.desc("n"), "w").limit(words - 1).collect()]


class Coder:
    """Token codes: 0 is the unknown word, `size` the start mark (as a context only)."""

    def __init__(self, words: list[bytes]):
        self.codes, self.size = {w: k + 1 for k, w in enumerate(words)}, len(words) + 1

    def pairs(self, text: str | None) -> np.ndarray:
        """context * size + word for each token."""
        get = self.codes.get
        words = tokens(text)
        ids = np.fromiter((get(w, 0) for w in words), np.int64, len(words))
        if not len(ids):
            return ids
        return np.concatenate([[self.size], ids[:-1]]) * self.size + ids


def bigrams(rows: DataFrame, coder: Coder) -> np.ndarray:
    """Counts (2, contexts, words) of a frame (text, in_target): all documents, then the target's."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[list, list] = ([], [])
        n = 0

        def done() -> pa.RecordBatch:
            codes, cols = [], []
            for part in held:
                k, c = np.unique(np.concatenate(part), return_counts=True) if part else (np.zeros(0, np.int64), np.zeros(0, np.int64))
                codes.append(k)
                cols.append(c.astype(np.int64))
                part.clear()
            rest, hit = [np.zeros(len(k), np.int64) for k in codes], [np.ones(len(k), np.int64) for k in codes]
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(codes)), pa.array(np.concatenate(cols)), pa.array(np.concatenate([rest[0], hit[1]]))], names=["p", "n", "target"])

        for batch in batches:
            for text, target in zip(batch.column(0), batch.column(1).to_pylist()):
                got = coder.pairs(text.as_py())
                if len(got):
                    held[bool(target)].append(got)
                    n += len(got)
                if n > _HELD:
                    yield done()
                    n = 0
        yield done()

    got = rows.mapInArrow(count, "p long, n long, target long").groupBy("p").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("target")).alias("t")).toPandas()
    out = np.zeros((2, (coder.size + 1) * coder.size))
    out[0, got["p"].to_numpy()] = got["n"].to_numpy()
    out[1, got["p"].to_numpy()] = got["t"].to_numpy()
    return out.reshape(2, coder.size + 1, coder.size)


def losses(counts: np.ndarray, weight: float) -> np.ndarray:
    """-log probability of each word after each context, from a table of bigram counts."""
    after, word = counts.sum(1, keepdims=True), counts.sum(0)
    plain = (word + 1) / (word.sum() + counts.shape[1])
    mixed = weight * counts / np.maximum(after, 1) + (1 - weight) * plain
    return -np.log(np.where(after > 0, mixed, plain[None]))


def score(docs: DataFrame, target_ids: DataFrame, words: int = WORDS, weight: float = WEIGHT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_tokens, target_loss, background_loss, score).

    target_ids: one column of ids of the documents that make the target set.
    """
    ids = base.stored(target_ids.select(F.col(target_ids.columns[0]).cast("long").alias("__target")).where("__target is not null").distinct(), "lm_target")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("t"))
    coder = Coder(vocabulary(rows.select("t"), words))
    marked = rows.join(base.checked_broadcast(ids), F.col("doc_id") == F.col("__target"), "left").select("t", F.col("__target").isNotNull().alias("in_target"))
    counts = bigrams(marked, coder)
    both = np.stack([losses(counts[1], weight).ravel(), losses(counts[0], weight).ravel()], 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pairs = [coder.pairs(t.as_py()) for t in batch.column(1)]
            n = np.array([len(p) for p in pairs], np.int64)
            mean = np.array([both[p].mean(0) if len(p) else (0.0, 0.0) for p in pairs]).reshape(-1, 2)
            none = n == 0
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n), pa.array(mean[:, 0], mask=none), pa.array(mean[:, 1], mask=none), pa.array(mean[:, 0] - mean[:, 1], mask=none)],
                names=["doc_id", "n_tokens", "target_loss", "background_loss", "score"],
            )

    return rows.mapInArrow(run, "doc_id long, n_tokens long, target_loss double, background_loss double, score double")


def hashed(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes of the contexts, hashes of the words, number of words of each text) of a column of texts, word after word."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(texts.fill_null("")))
    coded = lists.flatten().dictionary_encode()
    distinct = coded.dictionary.cast(pa.binary()).to_pylist()
    hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, distinct), np.uint64, len(distinct)).view(np.int64)
    at = coded.indices.to_numpy()
    real = np.array([len(w) > 0 for w in distinct], bool)[at]  # blanks at the ends leave empty words
    ends = np.concatenate([[0], np.cumsum(real)])
    cuts = lists.offsets.to_numpy()
    cuts = ends[cuts - cuts[0]]
    w, n = hashes[at[real]], np.diff(cuts)
    v = np.empty_like(w)
    v[1:] = w[:-1]
    v[cuts[:-1][n > 0]] = _START
    return v, w, n


def _pair(v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64 bits and 8 more of each bigram's hash."""
    v, w = v.view(np.uint64), w.view(np.uint64)
    return base.mix64(v * _STEP + w), (base.mix64(w * _STEP ^ v) >> np.uint64(56)).astype(np.uint8)


def _distinct(key: np.ndarray, more: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct keys in order, their further bits, the place of each given key among them)."""
    order = np.argsort(key)
    k, m = key[order], more[order]
    new = np.ones(len(k), bool)
    new[1:] = k[1:] != k[:-1]
    if (~new[1:] & (m[1:] != m[:-1])).any():  # equal in the first bits alone: order by all
        order = np.lexsort((more, key))
        k, m = key[order], more[order]
        new[1:] = (k[1:] != k[:-1]) | (m[1:] != m[:-1])
    place = np.empty(len(k), np.int64)
    place[order] = np.cumsum(new) - 1
    return k[new], m[new], place


def _packed(columns: list[np.ndarray], n: int) -> bytes:
    """Columns of n whole numbers below 2^64 each, byte by byte, compressed; after the number of rows."""
    planes = b"".join(np.ascontiguousarray(c).astype(np.uint64).view(np.uint8).reshape(n, 8).T.tobytes() for c in columns)
    return int(n).to_bytes(8, "little") + (pa.Codec("zstd").compress(planes, asbytes=True) if n else b"")


def _unpacked(blob: bytes, columns: int) -> list[np.ndarray]:
    n = int.from_bytes(blob[:8], "little")
    if not n:
        return [np.zeros(0, np.uint64)] * columns
    raw = pa.Codec("zstd").decompress(blob[8:], n * 8 * columns, asbytes=True)
    return [np.ascontiguousarray(x.T).view(np.uint64).ravel() for x in np.frombuffer(raw, np.uint8).reshape(columns, 8, n)]


class _Piece:
    """The words of a piece's texts: its distinct bigrams and words, sorted by hash whatever the order of the texts."""

    def __init__(self, texts: pa.ChunkedArray):
        found = [hashed(chunk.slice(lo, hi - lo)) for chunk in texts.chunks for lo, hi in base.slices(chunk, _HELD_BYTES)]
        v, w, self.sizes = (np.concatenate(x) if found else np.zeros(0, np.int64) for x in (zip(*found) if found else ((), (), ())))
        first = np.concatenate([[0], np.cumsum(self.sizes)])[:-1][self.sizes > 0]
        self.pairs, self.more, self.pair_at = _distinct(*_pair(v, w))
        every = np.append(w, _START).view(np.uint64)
        self.words, _, at = _distinct(every, np.zeros(len(every), np.uint8))
        self.word_at, start = at[:-1], at[-1]
        self.context_at = np.empty_like(self.word_at)
        self.context_at[1:] = self.word_at[:-1]
        self.context_at[first] = start

    def per_token(self, of_text: np.ndarray) -> np.ndarray:
        return np.repeat(of_text, self.sizes)


def _bounds(ranges: int) -> np.ndarray:
    """The least hash of each range after the first."""
    return np.array([-(-(r << 64) // ranges) for r in range(1, ranges)], np.uint64)


def _counted(ranges: int) -> Callable[[pa.Table], pa.Table]:
    """A piece (piece, doc_id, t, in_target) as rows (part, piece, pairs, words): its keys with their counts in all texts and in the target's."""

    def run(rows: pa.Table) -> pa.Table:
        x = _Piece(rows["t"])
        good = x.per_token(rows["in_target"].to_numpy().astype(float))
        count = lambda at, n: (np.bincount(at, minlength=n), np.bincount(at, good, n))
        b, t = count(x.pair_at, len(x.pairs))
        of_words = [*count(x.word_at, len(x.words)), *count(x.context_at, len(x.words))]
        cuts = [[0, *np.searchsorted(k, _bounds(ranges)), len(k)] for k in (x.pairs, x.words)]
        parts, pairs, words = [], [], []
        for r in range(ranges):
            (a, z), (c, d) = (cut[r : r + 2] for cut in cuts)
            if z > a or d > c:
                parts.append(r)
                pairs.append(_packed([np.diff(x.pairs[a:z], prepend=np.uint64(0)), x.more[a:z], b[a:z], t[a:z]], z - a))
                words.append(_packed([np.diff(x.words[c:d], prepend=np.uint64(0)), *[o[c:d] for o in of_words]], d - c))
        piece = pa.array([rows["piece"][0].as_py()] * len(parts), pa.int64())
        return pa.table([pa.array(parts, pa.int64()), piece, pa.array(pairs, pa.binary()), pa.array(words, pa.binary())], names=["part", "piece", "pairs", "words"])

    return run


def _summed(rows: pa.Table) -> pa.Table:
    """A range of hashes, as rows of `_counted`, to the same rows with the totals in place of the counts, without keys; the first row has the range's own totals."""
    out = {}
    for name, keyed in (("pairs", 2), ("words", 1)):
        got = [_unpacked(x.as_py(), keyed + (2 if keyed == 2 else 4)) for x in rows[name]]
        ends = np.cumsum([0, *[len(g[0]) for g in got]])
        key = np.concatenate([np.cumsum(g[0], dtype=np.uint64) for g in got])
        more = np.concatenate([g[1].astype(np.uint8) for g in got]) if keyed == 2 else np.zeros(len(key), np.uint8)
        k, _, at = _distinct(key, more)
        totals = [np.bincount(at, np.concatenate([g[c] for g in got]).astype(float), len(k)) for c in range(keyed, len(got[0]))]
        out[name] = [_packed([s[at[a:z]] for s in totals], z - a) for a, z in zip(ends, ends[1:])]
    b, t = totals[:2]
    own = [[int(x), *[0] * (len(rows) - 1)] for x in (b.sum(), t.sum(), np.count_nonzero(b))]
    columns = [rows["part"], rows["piece"], *[pa.array(out[c], pa.binary()) for c in ("pairs", "words")], *[pa.array(o, pa.int64()) for o in own]]
    return pa.table(columns, names=["part", "piece", "pairs", "words", "b", "t", "k"])


def _scored(weight: float, b: int, t: int, k: int) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """The documents of a piece with the totals of its keys, to rows of `score_whole`; b, t: words in all and in the target, k: distinct ones."""

    def run(rows: pa.Table, totals: pa.Table) -> pa.Table:
        x, totals = _Piece(rows["t"]), totals.sort_by("part")  # ranges in order are the keys in order
        read = lambda name, n: [np.concatenate(c).astype(float) for c in zip(*[_unpacked(blob.as_py(), n) for blob in totals[name]])]
        (pb, pt), (ub, ut, cb, ct) = read("pairs", 2), read("words", 4)
        if len(pb) != len(x.pairs) or len(ub) != len(x.words):
            raise RuntimeError(f"{len(pb)} and {len(ub)} totals came for {len(x.pairs)} bigrams and {len(x.words)} words")
        any_of = np.empty(len(x.pairs), np.int64)
        any_of[x.pair_at] = np.arange(len(x.pair_at))
        v, w, text = x.context_at[any_of], x.word_at[any_of], x.per_token(np.arange(len(x.sizes)))

        def mean(n: np.ndarray, context: np.ndarray, word: np.ndarray, tokens: int) -> np.ndarray:
            plain = (word[w] + 1) / float(tokens + k + 1)
            mixed = weight * n / np.maximum(context[v], 1) + (1 - weight) * plain
            loss = -np.log(np.where(context[v] > 0, mixed, plain))
            return np.bincount(text, loss[x.pair_at], len(x.sizes)) / np.maximum(x.sizes, 1)

        lt, lb, none = mean(pt, ct, ut, t), mean(pb, cb, ub, b), x.sizes == 0
        columns = [rows["doc_id"], pa.array(x.sizes.astype(np.int64)), *[pa.array(c, mask=none) for c in (lt, lb, lt - lb)]]
        return pa.table(columns, names=["doc_id", "n_tokens", "target_loss", "background_loss", "score"])

    return run


def score_whole(docs: DataFrame, target_ids: DataFrame, weight: float = WEIGHT, id_col: str = "doc_id", text_col: str = "text", most: int = _HOT) -> DataFrame:
    """Rows as of `score`, the vocabulary being every word of docs.

    most: bytes of text of a piece, about.
    """
    ids = base.stored(target_ids.select(F.col(target_ids.columns[0]).cast("long").alias("__target")).where("__target is not null").distinct(), "lm_target")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("t"))
    size = rows.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    pieces = -(-size // max(1, most)) or 1
    ranges = max(-(-size // _RANGE_BYTES), min(_RANGES, -(-size // _FIRST_BYTES)), 1)
    rows = rows.withColumn("piece", F.pmod(F.xxhash64("doc_id", "t"), F.lit(pieces).cast("long")))
    marked = rows.join(base.checked_broadcast(ids), F.col("doc_id") == F.col("__target"), "left").select("piece", "doc_id", "t", F.col("__target").isNotNull().alias("in_target"))
    sent = marked.groupBy("piece").applyInArrow(_counted(ranges), "part long, piece long, pairs binary, words binary")
    totals = base.stored(sent.groupBy("part").applyInArrow(_summed, "part long, piece long, pairs binary, words binary, b long, t long, k long"), "lm_totals")
    of = totals.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("b", "t", "k")]).first()
    back = totals.select("piece", "part", "pairs", "words").groupBy("piece")
    return rows.groupBy("piece").cogroup(back).applyInArrow(_scored(weight, of["b"], of["t"], of["k"]), "doc_id long, n_tokens long, target_loss double, background_loss double, score double")


def _rounded(spark: SparkSession, sf_dir: str, how: Callable[[DataFrame, DataFrame], DataFrame]) -> DataFrame:
    good = base.table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    out = how(base.table(spark, sf_dir, "documents"), good)
    return out.select("doc_id", "n_tokens", *[F.round(c, 6).alias(c) for c in ("target_loss", "background_loss", "score")])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target: documents labelled of good quality; losses rounded to 6 places."""
    return _rounded(spark, sf_dir, score)


def query_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As `query`, over every word."""
    return _rounded(spark, sf_dir, score_whole)


ORACLE = r"""
WITH tok AS (
  SELECT doc_id, unnest(words) AS w, generate_subscripts(words, 1) AS i
  FROM (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents)
), vocab AS (
  SELECT w FROM (SELECT w, count(*) AS n FROM tok GROUP BY w) ORDER BY n DESC, encode(w) LIMIT 1023
), coded AS (
  SELECT doc_id, i, CASE WHEN v.w IS NULL THEN '' ELSE tok.w END AS w FROM tok LEFT JOIN vocab v ON tok.w = v.w
), pair AS (
  SELECT doc_id, w, coalesce(lag(w) OVER (PARTITION BY doc_id ORDER BY i), '<start>') AS v,
         doc_id IN (SELECT doc_id FROM labels WHERE quality = 1) AS t FROM coded
), freq AS (
  SELECT v, w, count(*)::DOUBLE AS b, sum(t::INT)::DOUBLE AS t FROM pair GROUP BY v, w
), ctx AS (SELECT v, sum(b) AS b, sum(t) AS t FROM freq GROUP BY v),
uni AS (SELECT w, sum(b) AS b, sum(t) AS t FROM freq GROUP BY w),
total AS (SELECT sum(b) AS b, sum(t) AS t, (SELECT count(*) + 1 FROM vocab) AS k FROM freq),
prob AS (
  SELECT freq.v, freq.w,
    CASE WHEN ctx.b > 0 THEN 0.7::DOUBLE * freq.b / ctx.b + 0.3::DOUBLE * (uni.b + 1) / (total.b + k) ELSE (uni.b + 1) / (total.b + k) END AS pb,
    CASE WHEN ctx.t > 0 THEN 0.7::DOUBLE * freq.t / ctx.t + 0.3::DOUBLE * (uni.t + 1) / (total.t + k) ELSE (uni.t + 1) / (total.t + k) END AS pt
  FROM freq JOIN ctx USING (v) JOIN uni ON freq.w = uni.w CROSS JOIN total
), per AS (
  SELECT doc_id, count(*) AS n_tokens, avg(-ln(pt)) AS lt, avg(-ln(pb)) AS lb FROM pair JOIN prob USING (v, w) GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_tokens, 0)::BIGINT AS n_tokens, round(lt, 6) AS target_loss, round(lb, 6) AS background_loss, round(lt - lb, 6) AS score
FROM documents d LEFT JOIN per USING (doc_id)
"""

#: The same over every word.
ORACLE_WHOLE = ORACLE.replace("LIMIT 1023", "")
