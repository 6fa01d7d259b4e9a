"""Operator 8: SentencePiece (BPE) encoding by a prefix table, and decoding.

For every prefix of a string the encoder keeps one number: the last token of
that prefix's encoding.  Token t can be the last token of a prefix ending at i
exactly if t ends there (an Aho-Corasick automaton over the vocabulary reports
all such t) and t is *compatible* with the last token p of the prefix before
it: encoding p's and t's strings joined gives p, t again.  Exactly one token
passes, so the table fills left to right and ids are read off backwards.

Compatibility is decided from merge trees.  A token's tree is how the merge
rule (best-ranked piece first, leftmost on ties, any adjacent pair whose
joined string is a piece) builds it; its parts on the border exist from the
merge that makes them to the merge that consumes them.  p and t are
incompatible if a border part of each exist at once and joining them ranks
before what would consume either.  Answers are remembered by pair.

Runs of word marks are pieces that all tie, and rank last: leftmost merging
joins them from the left, out of the marks that no word takes.

No piece has a word mark after another character, and characters outside the
vocabulary join nothing (they become byte tokens), so a text is cut before
word marks and around such characters, and each distinct string is encoded
once per worker.  All of it is checked against the library in the tests.

Nulls and empty texts have the begin and end ids alone.  Texts of any length
are encoded whole in time linear in their length.
"""

from __future__ import annotations

import hashlib
import re
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

MARK = "▁"
CACHE_CHUNKS = 250_000
CACHE_PAIRS = 1_000_000
#: Characters decoded at a time.
DECODE_CHARS = 2_000_000


class PrefixTableEncoder:
    """ids as the sentencepiece library gives them for a BPE model with byte fallback."""

    def __init__(self, model: str):
        import ahocorasick
        import public_tokenizers
        import sentencepiece

        self.lib = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(model))
        lib, n = self.lib, self.lib.get_piece_size()
        plain = [i for i in range(n) if not (lib.is_control(i) or lib.is_unknown(i) or lib.is_byte(i))]
        self.ids = {lib.id_to_piece(i): i for i in plain}
        self.rank = {p: -lib.get_score(i) for p, i in self.ids.items()}
        self.bytes = [lib.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.n, self.begin, self.end = n, struct.pack("<I", lib.bos_id()), struct.pack("<I", lib.eos_id())
        if any(re.search(f"[^{MARK}]{MARK}", p) for p in self.ids):
            raise ValueError("the vocabulary has pieces with a word mark inside; texts cannot be cut before marks")
        self.runs = {len(p): i for p, i in self.ids.items() if set(p) == {MARK}}
        self.longest = max(self.runs)
        scores = [r for p, r in self.rank.items() if len(p) > 1 and set(p) != {MARK}]
        if len(set(scores)) < len(scores) or any(MARK + MARK in p and set(p) != {MARK} for p in self.ids):
            raise ValueError("the vocabulary has tied pieces, or word marks beside them, that this encoder does not know")
        self.known_chars = {c for p in self.ids for c in p}
        self.left: list = [()] * n
        self.right: list = [()] * n
        self.size = [0] * n
        self.automaton = ahocorasick.Automaton()
        for p, i in self.ids.items():
            if len(p) > 1 and i in self.runs.values():
                continue
            tree = self._tree(p)
            if tree is not None:  # pieces that the rule never builds cannot be tokens
                self.left[i], self.right[i] = self._border(tree, 0), self._border(tree, 1)
                self.size[i] = len(p)
                self.automaton.add_word(p, i)
        self.automaton.make_automaton()
        self.pairs: dict[int, bool] = {}
        self.chunks = base.TwoGenerationCache(CACHE_CHUNKS)

    def _tree(self, piece: str):
        """(string, time, left, right) of the merges that build a piece, or None."""
        nodes = [(c, -1e30, None, None) for c in piece]
        while len(nodes) > 1:
            best = min(((self.rank.get(a[0] + b[0], np.inf), k) for k, (a, b) in enumerate(zip(nodes, nodes[1:]))))
            if best[0] == np.inf:
                return None
            a, b = nodes[best[1] : best[1] + 2]
            nodes[best[1] : best[1] + 2] = [(a[0] + b[0], max(best[0], a[1], b[1]), a, b)]
        return nodes[0]

    @staticmethod
    def _border(tree, side: int) -> list[tuple[str, float, float]]:
        """Parts at one end, whole first: (string, made, consumed)."""
        out, until = [], np.inf
        while tree is not None:
            out.append((tree[0], tree[1], until))
            until, tree = tree[1], tree[2 + side]
        return out

    def _compatible(self, p: int, t: int) -> bool:
        rank = self.rank.get
        for a, made_a, gone_a in self.right[p]:
            for b, made_b, gone_b in self.left[t]:
                m = rank(a + b)
                if m is not None and m < gone_a and m <= gone_b and made_a < gone_b and made_b < gone_a:
                    return False
        return True

    def _marks(self, n: int) -> list[int]:
        """ids of n marks that only join each other, leftmost pair first; no run joins a longest one."""
        stack: list[int] = []
        for _ in range(n):
            stack.append(1)
            while len(stack) > 1 and stack[-2] + stack[-1] in self.runs:
                stack[-2:] = [stack[-2] + stack[-1]]
        return [self.runs[k] for k in stack]

    def _encode(self, chunks: list[str]) -> list[bytes]:
        """ids of strings that hold only vocabulary characters, or one other character."""
        n, pairs, size, compatible = self.n, self.pairs, self.size, self._compatible
        if len(pairs) > CACHE_PAIRS:
            pairs.clear()
        whole, out, pack = self.ids.get, [], struct.pack
        for s in chunks:
            if len(s) == 1 and s not in self.known_chars:
                ids = [self.bytes[b] for b in s.encode()]
                out.append(pack(f"<{len(ids)}I", *ids))
                continue
            marks = 0
            if s.startswith(MARK + MARK):
                marks = len(s) - len(s.lstrip(MARK)) - 1
                s = s[marks:]
            i = whole(s)
            if not marks and i is not None and size[i]:
                out.append(pack("<I", i))
                continue
            last = [-1] * len(s)
            for at, t in self.automaton.iter(s):
                if last[at] >= 0:
                    continue
                before = at - size[t]
                if before < 0:
                    last[at] = t
                    continue
                p = last[before]
                ok = pairs.get(p * n + t)
                if ok is None:
                    ok = pairs[p * n + t] = p >= 0 and compatible(p, t)
                if ok:
                    last[at] = t
            ids, at = [], len(s) - 1
            while at >= 0:
                t = last[at]
                if t < 0:  # a character that only occurs inside longer pieces
                    ids.extend(self.bytes[b] for b in reversed(s[at].encode()))
                    at -= 1
                else:
                    ids.append(t)
                    at -= size[t]
            ids.reverse()
            if marks:
                if ids[0] == self.runs[1]:
                    marks, ids = marks + 1, ids[1:]
                full, rest = divmod(marks, self.longest)
                ids = [self.runs[self.longest]] * full + self._marks(rest) + ids
            out.append(pack(f"<{len(ids)}I", *ids))
        return out

    def _cut(self, text: str) -> list[str]:
        s = MARK + text.replace(" ", MARK)
        if "\0" in s or MARK + MARK in s:
            cut = re.findall(f"{MARK}+[^{MARK}\n]*|[^{MARK}\n]+|\n", s)
        else:
            cut = s.replace(MARK, "\0" + MARK).replace("\n", "\0\n\0").split("\0")
        return cut

    def _make(self, chunks: list[str]) -> list[bytes]:
        known = self.known_chars
        odd = {s: None for s in chunks if len(s) > 1 and not known.issuperset(s)}
        if not odd:
            return self._encode(chunks)
        parts = {}
        for s in odd:
            cut: list[str] = []
            run = ""
            for c in s:
                if c in known:
                    run += c
                else:
                    cut += [run, c] if run else [c]
                    run = ""
            parts[s] = [*cut, run] if run else cut
        plain = [s for s in chunks if s not in odd]
        found = dict(zip(plain, self._encode(plain)))
        todo = list({p for cut in parts.values() for p in cut} - found.keys())
        found.update(zip(todo, self._encode(todo)))
        return [found[s] if s not in odd else b"".join([found[p] for p in parts[s]]) for s in chunks]

    def encode(self, text: str) -> bytes:
        """ids with begin and end as little-endian unsigned 32-bit integers."""
        if not text:
            return self.begin + self.end
        chunks = [c for c in self._cut(text) if c]
        known = self.chunks.ensure(chunks, self._make)
        return b"".join([self.begin, *[known[c] for c in chunks], self.end])

    def decode(self, ids: list[bytes]) -> list[str]:
        return self.lib.decode([np.frombuffer(b, "<u4").tolist() for b in ids], num_threads=1)


def encoder(model: str) -> PrefixTableEncoder:
    """This worker's encoder; workers outlive tasks, so strings stay known."""
    return base.held(("pieces", model), lambda: PrefixTableEncoder(model))


def encode_decode(docs: DataFrame, model: str = "piece_bpe_32k.model", id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """One row per document: its id, n_tokens, and ids with the decoded text or (digest) their sha256.

    No shuffle: texts are encoded where they are read.
    """
    rows = docs.select(F.col(id_col).alias("d"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    kind = "string" if digest else "array<long>"
    id_type = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(model)

        def emit(keys, ids: list[bytes]) -> pa.RecordBatch:
            texts = enc.decode(ids)
            counts = pa.array([len(b) // 4 for b in ids], pa.int64())
            if digest:
                a = pa.array([hashlib.sha256(b).hexdigest() for b in ids], pa.string())
                b = pa.array([hashlib.sha256(t.encode()).hexdigest() for t in texts], pa.string())
            else:
                a = pa.array([np.frombuffer(b, "<u4").astype(np.int64) for b in ids], pa.list_(pa.int64()))
                b = pa.array(texts, pa.string())
            return pa.RecordBatch.from_arrays([keys, counts, a, b], names=["doc_id", "n_tokens", "ids", "decoded"])

        for batch in batches:
            keys, held, since, size = batch.column(0), [], 0, 0
            for k, text in enumerate(batch.column(1)):
                text = text.as_py()
                held.append(enc.encode(text))
                size += len(text)
                if size >= DECODE_CHARS:
                    yield emit(keys.slice(since, len(held)), held)
                    held, since, size = [], k + 1, 0
            if held:
                yield emit(keys.slice(since, len(held)), held)

    out = rows.mapInArrow(run, f"doc_id {id_type}, n_tokens long, ids {kind}, decoded string")
    return out.toDF(id_col, "n_tokens", "ids_sha256", "decoded_sha256") if digest else out.toDF(id_col, "n_tokens", "ids", "decoded")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(base.table(spark, sf_dir, "documents"), digest=True)
