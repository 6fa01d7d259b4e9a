"""Operator 5: language identification by segmentation-marginalised unigrams.

Every language has a probability for each piece of a fixed public vocabulary.
A word's probability under a language is the sum over *all* ways to cut it
into pieces, by a forward recurrence over its characters; a document's is the
product over its words, and the languages' posterior (equal priors) decides.

Piece probabilities are learned by expectation maximisation (expected piece
counts from forward and backward sums) on word counts of a bounded sample of
labelled rows: about `sample_docs` whole documents of each language, chosen by
a hash of the id.  All else covers every row and the whole text.

Words are runs of characters between blanks; only their letters count, in
lower case, behind a word mark.  Words and pieces may have any length: many
words of up to `SHORT_WORD` letters are summed at once, a longer one (scripts
without blanks) alone, in scaled numbers over a window of the longest piece.
Pieces with capitals, digits or marks never occur in such words and are left
out.  A letter outside the vocabulary costs the same in each language.
Distinct words are scored once per worker.

A null text, or one without a letter, gets `und` with score 0.  Null languages
are not learned from; an empty training set gives `und` throughout.  Ties go to
the alphabetically first language.  Ids may be null or repeated.  Very long
texts are scored some words at a time.  An empty table gives no rows.  Of the
other columns, `lang_pred` and `score` are replaced and all others kept.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

MARK = "▁"
#: No vocabulary with longer pieces is taken.
MAX_PIECE = 64
#: Letters of words that are summed many at a time (their probabilities fit a double); longer ones are summed alone.
SHORT_WORD = 32
UNDETERMINED = "und"
#: Probability of a letter that is in no piece, in any language.
STRANGE = 1e-7
#: Words a worker remembers with their scores.
CACHE_WORDS = 150_000
#: Words looked up at a time.
HELD_WORDS = 100_000
_BASE = np.uint64(0x9E3779B97F4A7C15)


def _hashes(texts: list[str]) -> np.ndarray:
    """Rolling hash of each (short) text."""
    n = max(map(len, texts))
    codes = np.zeros((len(texts), n), np.uint64)
    for i, t in enumerate(texts):
        codes[i, : len(t)] = np.frombuffer(t.encode("utf-32-le"), "<u4")
    h, out = np.zeros(len(texts), np.uint64), np.zeros(len(texts), np.uint64)
    sizes = np.array([len(t) for t in texts])
    for k in range(n):
        h = h * _BASE + codes[:, k] + np.uint64(1)
        out[sizes == k + 1] = h[sizes == k + 1]
    return out


class Vocabulary:
    """Lower-case pieces of a public model, found by a rolling hash (exact: built without collisions)."""

    def __init__(self, model: str):
        import public_tokenizers
        import sentencepiece

        lib = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(model))
        pieces = [lib.id_to_piece(i) for i in range(lib.get_piece_size()) if not (lib.is_control(i) or lib.is_unknown(i) or lib.is_byte(i))]
        self.pieces = [p for p in pieces if p == p.lower() and all(c == MARK or c.isalpha() for c in p) and MARK not in p[1:]]
        self.longest = max(map(len, self.pieces))
        if self.longest > MAX_PIECE:
            raise ValueError(f"a piece of {self.longest} characters")
        h = _hashes(self.pieces)
        order = np.argsort(h)
        self.hash, self.id = h[order], order.astype(np.int32)
        if (self.hash[1:] == self.hash[:-1]).any():
            raise ValueError("two pieces share a hash")
        self.filter = np.zeros(1 << 22, bool)
        self.filter[(self.hash * _BASE) >> np.uint64(42)] = True

    def find(self, h: np.ndarray) -> np.ndarray:
        """Piece numbers of substring hashes; len(pieces) where there is none."""
        out = np.full(len(h), len(self.pieces), np.int32)
        may = np.flatnonzero(self.filter[(h * _BASE) >> np.uint64(42)])
        at = np.minimum(np.searchsorted(self.hash, h[may]), len(self.hash) - 1)
        hit = self.hash[at] == h[may]
        out[may[hit]] = self.id[at[hit]]
        return out


class Lattice:
    """All pieces in all words: for each end and length the words' piece numbers. Words are sorted, longest first."""

    def __init__(self, words: list[str], vocabulary: Vocabulary):
        self.order = sorted(range(len(words)), key=lambda k: -len(words[k]))
        marked = [MARK + words[k] for k in self.order]
        sizes = np.array([len(w) for w in marked])
        n = int(sizes[0]) if len(sizes) else 0
        codes = np.frombuffer("".join(w.ljust(n, "\0") for w in marked).encode("utf-32-le"), "<u4").reshape(len(marked), n).astype(np.uint64)
        prefix = np.zeros((n + 1, len(marked)), np.uint64)
        for k in range(n):
            prefix[k + 1] = prefix[k] * _BASE + codes[:, k] + np.uint64(1)
        power = [np.uint64(1)]
        with np.errstate(over="ignore"):
            for _ in range(vocabulary.longest):
                power.append(power[-1] * _BASE)
        self.words, self.sizes = len(marked), sizes
        #: Words of at least k characters.
        self.live = [int(np.searchsorted(-sizes, -k, side="right")) for k in range(n + 1)]
        none = len(vocabulary.pieces)
        self.steps: list[tuple[int, int, np.ndarray, np.ndarray]] = []
        self.lost: list[np.ndarray] = [np.zeros(0, int)]
        for end in range(1, n + 1):
            m = self.live[end]
            for size in range(1, min(vocabulary.longest, end) + 1):
                ids = vocabulary.find(prefix[end, :m] - prefix[end - size, :m] * power[size])
                at = np.flatnonzero(ids < none)
                if size == 1:
                    self.lost.append(np.flatnonzero(ids == none))
                if len(at):
                    self.steps.append((end, size, at, ids[at]))

    def forward(self, p: np.ndarray) -> np.ndarray:
        """(length + 1, words, languages): summed probability of all segmentations of each prefix."""
        a = np.zeros((len(self.live), self.words, p.shape[1]))
        if self.words:
            a[0] = 1.0
        end_before = 0
        for end, size, at, ids in [*self.steps, (len(self.live), 0, None, None)]:
            while end_before < end:  # a letter outside the vocabulary is a piece of its own
                end_before += 1
                if end_before < len(self.live):
                    a[end_before, self.lost[end_before]] = a[end_before - 1, self.lost[end_before]] * STRANGE
            if size:
                a[end, at] += a[end - size, at] * p[ids]
        return a

    def totals(self, p: np.ndarray) -> np.ndarray:
        """Log probability of each word (in its given order) under each language."""
        out = np.zeros((self.words, p.shape[1]))
        if self.words:
            a = self.forward(p)
            out[np.array(self.order)] = np.log(np.maximum(a[self.sizes, np.arange(self.words)], 1e-300))
        return out

    def expected(self, p: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Expected counts of the pieces in words met counts times, under one language."""
        a = self.forward(p[:, None])[:, :, 0]
        b = np.zeros_like(a)
        b[self.sizes, np.arange(self.words)] = 1.0
        weight = counts[np.array(self.order)] / np.maximum(a[self.sizes, np.arange(self.words)], 1e-300)
        out = np.zeros(len(p))
        steps = self.steps[::-1]
        k = 0
        for end in range(len(self.live) - 1, 0, -1):
            lost = self.lost[end]
            b[end - 1, lost] += b[end, lost] * STRANGE
            while k < len(steps) and steps[k][0] == end:
                _, size, at, ids = steps[k]
                flow = b[end, at] * p[ids]
                b[end - size, at] += flow
                np.add.at(out, ids, a[end - size, at] * flow * weight[at])
                k += 1
        return out


class LongWord:
    """All pieces in one word of any length; sums are scaled position by position, so that nothing vanishes."""

    def __init__(self, word: str, vocabulary: Vocabulary):
        codes = np.frombuffer((MARK + word).encode("utf-32-le"), "<u4").astype(np.uint64)
        self.n, self.longest, none = len(codes), vocabulary.longest, len(vocabulary.pieces)
        #: ids[end, size - 1]: number of the piece of that size that ends there; none + 1: of no piece.
        self.ids = np.full((self.n + 1, self.longest), none + 1, np.int32)
        h = np.zeros(self.n, np.uint64)
        with np.errstate(over="ignore"):
            for size in range(1, min(self.longest, self.n) + 1):
                h = h[: self.n - size + 1] * _BASE + codes[size - 1 :] + np.uint64(1)
                found = vocabulary.find(h)
                found[found == none] = none if size == 1 else none + 1  # a letter outside is a piece of its own
                self.ids[size:, size - 1] = found

    def _chances(self, p: np.ndarray) -> np.ndarray:
        """p with the strange letter's and no piece's probability below it."""
        return np.concatenate([p, np.full((1, p.shape[1]), STRANGE), np.zeros((1, p.shape[1]))])

    def forward(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(scaled sums of each prefix, logarithm of the scale of each), per language."""
        q, n, k = self._chances(p), self.n, self.longest
        a, scale = np.zeros((n + 1, p.shape[1])), np.zeros((n + 1, p.shape[1]))
        a[0] = 1.0
        back = np.zeros((k, p.shape[1]))  # the last sums, newest first, in the newest one's scale
        back[0] = 1.0
        for end in range(1, n + 1):
            v = np.einsum("ij,ij->j", back, q[self.ids[end]])
            scale[end], a[end] = scale[end - 1] + np.log(v), 1.0
            back[1:] = back[:-1] / v
            back[0] = 1.0
        return a, scale

    def total(self, p: np.ndarray) -> np.ndarray:
        """Log probability under each language."""
        return self.forward(p)[1][self.n]

    def expected(self, p: np.ndarray) -> np.ndarray:
        """Expected counts of the pieces, under one language."""
        q, n, k = self._chances(p[:, None])[:, 0], self.n, self.longest
        _, up = self.forward(p[:, None])
        up = up[:, 0]
        down = np.zeros(n + 1)  # logarithms of the sums of each suffix
        ahead = np.zeros(k)  # the next sums, nearest first, in the nearest one's scale
        ahead[0] = 1.0
        sizes = np.arange(k)
        for at in range(n - 1, -1, -1):
            ends = at + 1 + sizes
            ok = ends <= n
            v = float((ahead[ok] * q[self.ids[ends[ok], sizes[ok]]]).sum())
            down[at] = down[at + 1] + np.log(v)
            ahead[1:] = ahead[:-1] / v
            ahead[0] = 1.0
        out = np.zeros(len(q))
        for size in range(1, min(k, n) + 1):
            ids = self.ids[size:, size - 1]
            np.add.at(out, ids, np.exp(up[: n - size + 1] + down[size:] - up[n]) * q[ids])
        return out[: len(p)]


@dataclass
class Model:
    """Piece probabilities of each language, over the pieces of a public vocabulary."""

    vocabulary: str
    languages: list[str]
    probability: np.ndarray  # (pieces, languages)


def letters(word: str) -> str:
    return word.lower() if word.isalpha() else "".join(filter(str.isalpha, word.lower()))


def log_chances(words: list[str], vocabulary: Vocabulary, p: np.ndarray) -> np.ndarray:
    """Log probability of each of the (letters of) words under each language."""
    out = np.zeros((len(words), p.shape[1]))
    short = [k for k, w in enumerate(words) if len(w) <= SHORT_WORD]
    for s in range(0, len(short), 20_000):
        out[short[s : s + 20_000]] = Lattice([words[k] for k in short[s : s + 20_000]], vocabulary).totals(p)
    for k, w in enumerate(words):
        if len(w) > SHORT_WORD:
            out[k] = LongWord(w, vocabulary).total(p)
    return out


def train(labelled: DataFrame, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", vocabulary: str = "piece_bpe_32k.model", sample_docs: int = 400, rounds: int = 4, smooth: float = 0.05) -> Model:
    """Learn from about sample_docs documents of each non-null language of `labelled`."""
    known = labelled.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    sizes = {r[0]: r[1] for r in known.groupBy(lang_col).count().collect()}
    languages = sorted(sizes)
    unit = (F.xxhash64(F.lit("sample"), F.col(id_col).cast("string")) % 1_000_000 + 1_000_000) % 1_000_000
    share = F.create_map(*[F.lit(x) for k in languages for x in (k, min(1.0, sample_docs / sizes[k]))]) if languages else None
    vocab = Vocabulary(vocabulary)
    p = np.full((len(vocab.pieces), len(languages)), 1.0 / max(1, len(vocab.pieces)))
    if not languages:
        return Model(vocabulary, [], p)
    sample = known.where(unit < share[F.col(lang_col)] * 1_000_000).select(F.col(lang_col).alias("l"), F.col(text_col).alias("t"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found: Counter = Counter()
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                for w, n in Counter(text.as_py().split()).items():
                    if s := letters(w):
                        found[lang, s] += n
            keys = list(found)
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.string()), pa.array(list(found.values()), pa.int64())], names=["l", "w", "n"])

    words = sample.mapInArrow(count, "l string, w string, n long").groupBy("l", "w").agg(F.sum("n").alias("n")).toPandas()
    for k, lang in enumerate(languages):
        own = words[words["l"] == lang].sort_values("w")
        long = own[own["w"].str.len() > SHORT_WORD]
        own = own[own["w"].str.len() <= SHORT_WORD]
        counts, cells, q = own["n"].to_numpy(np.float64), [], p[:, k]
        for s in range(0, len(own), 50_000):
            cells.append((Lattice(own["w"].tolist()[s : s + 50_000], vocab), counts[s : s + 50_000]))
        alone = [(LongWord(x, vocab), float(n)) for x, n in zip(long["w"], long["n"])]
        for _ in range(rounds):
            got = sum((lattice.expected(q, c) for lattice, c in cells), np.zeros(len(q))) + smooth
            got = sum((n * x.expected(q) for x, n in alone), got)
            q = got / got.sum()
        p[:, k] = q
    return Model(vocabulary, languages, p)


class Scorer:
    """Log probabilities of words under each language, remembered."""

    def __init__(self, model: Model):
        self.model, self.vocabulary = model, Vocabulary(model.vocabulary)
        self.p = model.probability
        self._clear()

    def _clear(self) -> None:
        self.index: dict[str, int] = {}
        self.scores = np.zeros((1024, len(self.model.languages) + 1))  # the last column: number of letters

    def rows(self, words: list[str]) -> np.ndarray:
        """Row numbers in `scores` of the words."""
        index = self.index
        new = [w for w in dict.fromkeys(words) if w not in index]
        if new and len(index) + len(new) > CACHE_WORDS and index:
            self._clear()
            index, new = self.index, list(dict.fromkeys(words))
        if new:
            plain = [letters(w) for w in new]
            distinct = list(dict.fromkeys(filter(None, plain)))
            table = np.concatenate([log_chances(distinct, self.vocabulary, self.p), np.zeros((1, self.p.shape[1]))])
            where = {s: k for k, s in enumerate(distinct)}
            got = table[[where[w] if w else len(distinct) for w in plain]]
            n = len(index)
            while n + len(new) > len(self.scores):
                self.scores = np.concatenate([self.scores, np.zeros_like(self.scores)])
            self.scores[n : n + len(new), :-1] = got
            self.scores[n : n + len(new), -1] = [len(w) for w in plain]
            index.update(zip(new, range(n, n + len(new))))
        return np.fromiter(map(index.__getitem__, words), np.int64, len(words))

    def documents(self, texts: Iterable[str | None]) -> Iterator[tuple[str, float]]:
        """(language, posterior) of each text; new words of many texts are scored at once."""
        held: list[str] = []
        cuts = [0]
        rest = 0.0  # of a long text whose words do not fit at once
        for text in texts:
            words = (text or "").split()
            while len(words) > HELD_WORDS:
                rest = rest + self.scores_of(words[:HELD_WORDS]).sum(0)
                words = words[HELD_WORDS:]
            if not isinstance(rest, float):
                yield from self._decide(held, cuts)
                held, cuts = [], [0]
                yield self._best(rest + self.scores_of(words).sum(0))
                rest = 0.0
                continue
            held += words
            cuts.append(len(held))
            if len(held) > HELD_WORDS:
                yield from self._decide(held, cuts)
                held, cuts = [], [0]
        yield from self._decide(held, cuts)

    def document(self, text: str | None) -> tuple[str, float]:
        return next(self.documents([text]))

    def scores_of(self, words: list[str]) -> np.ndarray:
        rows = self.rows(words)
        return self.scores[rows]

    def _decide(self, words: list[str], cuts: list[int]) -> Iterator[tuple[str, float]]:
        if len(cuts) > 1:
            sums = np.concatenate([np.zeros((1, self.scores.shape[1])), np.cumsum(self.scores_of(words), 0)])
            yield from map(self._best, sums[cuts[1:]] - sums[cuts[:-1]])

    def _best(self, total: np.ndarray) -> tuple[str, float]:
        if not self.model.languages or total[-1] < 0.5:
            return UNDETERMINED, 0.0
        best = int(np.argmax(total[:-1]))
        return self.model.languages[best], float(1.0 / np.exp(total[:-1] - total[best]).sum())


def identify(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """docs with lang_pred and score (replacing columns of these names); no shuffle."""
    keep = [c for c in docs.columns if c not in ("lang_pred", "score")]
    rows = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`").alias("__text"))
    schema = docs.select(*[F.col(f"`{c}`") for c in keep]).schema.add("lang_pred", "string").add("score", "double")
    key = ("language", model.vocabulary, tuple(model.languages), hash(model.probability.tobytes()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = base.held(key, lambda: Scorer(model))
        for batch in batches:
            got = list(scorer.documents(t.as_py() for t in batch.column(batch.num_columns - 1)))
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:-1], pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())],
                names=[*batch.schema.names[:-1], "lang_pred", "score"],
            )

    return rows.mapInArrow(run, schema)


def fold(id_col: str, n: int) -> Column:
    """crc32 of the id's text modulo n (null ids: of the empty text)."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % n


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = base.table(spark, sf_dir, "documents")
    model = train(docs.where(fold("doc_id", 3) != 1))
    out = identify(docs.select("doc_id", "text"), model).withColumn("held_out", fold("doc_id", 3) == 1)
    return out.select("doc_id", "held_out", "lang_pred", "score")
