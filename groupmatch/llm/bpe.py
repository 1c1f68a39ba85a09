"""Exact byte-level BPE encoding with a minimal acyclic transducer of frequent words.

A Spark pass finds the corpus' frequent words with mergeable heavy-hitter summaries. They
are compiled into a minimal acyclic automaton whose arcs carry outputs that add up to the
word's number, so that suffixes are shared although every word has its own ids. The compiled
arrays are one block of bytes, opened through a memory map. A batch's distinct words walk the
automaton in lockstep; words outside it go through exact merges, many at a time.
"""

from __future__ import annotations

import hashlib
import json
import mmap
import struct
import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textops import PIECE, _tables, batches, give_back, mix, sliced, take_spans, trimmed, utf8

#: Bytes of text that are split and merged together; a longer text is taken alone.
GROUP = PIECE
_LETTER, _NUMBER, _BLANK, _REST = 0, 1, 2, 3
_kinds: list[np.ndarray] = []
#: The Unicode white space property.
_WHITE = [*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]


def kind_table() -> np.ndarray:
    """Letter, number, white space or other, by code point."""
    if not _kinds:
        t = np.full(0x110000, _REST, np.uint8)
        for cp in range(0x110000):
            c = unicodedata.category(chr(cp))[0]
            if c == "L":
                t[cp] = _LETTER
            elif c == "N":
                t[cp] = _NUMBER
        t[_WHITE] = _BLANK
        _kinds.append(t)
    return _kinds[0]


def word_starts(points: np.ndarray, texts: np.ndarray) -> np.ndarray:
    """Sorted positions (code points) where words begin, for concatenated texts.

    `texts` holds each text's first position. A word is a run of letters, numbers or other
    signs with at most one blank before it; white space before a word gives its last
    character to it or stands alone; an apostrophe takes the letters s, t, m, d, re, ve or ll."""
    n = len(points)
    kind = kind_table()[points]
    border = np.zeros(n + 1, bool)
    border[texts] = True
    border[n] = True
    cut = border.copy()
    cut[1:n] |= kind[1:] != kind[:-1]
    white = kind == _BLANK
    # The last white space before other signs, within one text, starts a word of its own ...
    last = np.flatnonzero(white[:-1] & ~white[1:] & ~border[1:n]) if n > 1 else np.zeros(0, np.int64)
    cut[last] = True
    # ... and a plain blank joins what follows.
    cut[last[points[last] == 0x20] + 1] = False
    # Apostrophes that begin a word, alone in their run, before letters.
    quote = np.flatnonzero(points == 0x27)
    if len(quote):
        quote = quote[cut[quote] & (quote + 1 < n)]
        after = quote + 1
        quote, after = quote[kind[after] == _LETTER], after[kind[after] == _LETTER]
        ok = ~border[after]
        quote, after = quote[ok], after[ok]
        first = points[after]
        second = np.where((after + 1 < n) & ~border[np.minimum(after + 1, n)], points[np.minimum(after + 1, n - 1)], 0)
        one = np.isin(first, [ord(c) for c in "stmd"])
        two = ((first == ord("r")) | (first == ord("v"))) & (second == ord("e")) | (first == ord("l")) & (second == ord("l"))
        hit = one | two
        cut[after[hit]] = False
        cut[after[hit] + np.where(one, 1, 2)[hit]] = True
    return np.flatnonzero(cut[:n])


def words_of(texts: list[bytes]):
    """(buffer, first byte and length of each word, first word of each text) of joined texts."""
    points = [np.frombuffer(t.decode("utf-8").encode("utf-32-le"), np.uint32) for t in texts]
    sizes = np.array([len(p) for p in points])
    flat = np.concatenate(points) if points else np.zeros(0, np.uint32)
    firsts = np.concatenate(([0], np.cumsum(sizes)))[:-1]
    cuts = word_starts(flat, firsts[sizes > 0]) if len(flat) else np.zeros(0, np.int64)
    width = 1 + (flat >= 0x80).astype(np.int64) + (flat >= 0x800) + (flat >= 0x10000)
    at = np.concatenate(([0], np.cumsum(width)))
    ends = np.append(cuts[1:], len(flat)).astype(np.int64)
    begin = at[cuts]
    return b"".join(texts), begin, at[ends] - begin, np.searchsorted(cuts, np.append(firsts, len(flat)))


def span_hashes(buffer: bytes, begin: np.ndarray, length: np.ndarray) -> np.ndarray:
    raw = np.frombuffer(buffer, np.uint8)
    up, down = _tables(len(raw) + 1)
    sums = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)], out=sums[1:])
    return mix((sums[begin + length] - sums[begin]) * down[begin] + mix(length.astype(np.uint64)))


class Vocabulary:
    """Ids of bytes, ranks of merges and bytes of ids, from a tokenizer file's contents."""

    def __init__(self, raw: bytes):
        spec = json.loads(raw)
        # Bytes that stand for themselves in a token's letters.
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        letters = {b: chr(b) for b in printable}
        for k, b in enumerate(x for x in range(256) if x not in letters):
            letters[b] = chr(256 + k)
        back = {c: b for b, c in letters.items()}
        vocab = spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*vocab.values(), *self.special.values()]) + 1
        texts = [b""] * size
        for token, i in vocab.items():
            texts[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in self.special.items():
            texts[i] = token.encode()
        self.lengths = np.array([len(t) for t in texts], np.int64)
        self.begins = np.concatenate(([0], np.cumsum(self.lengths)))[:-1]
        self.flat = np.frombuffer(b"".join(texts), np.uint8)
        self.byte_ids = np.array([vocab[letters[b]] for b in range(256)], np.int64)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        keys = np.array([(vocab[a] << 32) | vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys)
        self.pair_keys, self.pair_ranks = keys[order], order.astype(np.int64)
        self.merged = np.array([vocab[a + b] for a, b in pairs], np.int64)

    def rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of each pair; a large number if the pair never merges."""
        key = (a << 32) | b
        at = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
        return np.where(self.pair_keys[at] == key, self.pair_ranks[at], 1 << 40)

    def merge(self, buffer: bytes, begin: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all spans, number of ids of each), merging best pairs of all spans in step."""
        sym = self.byte_ids[take_spans(np.frombuffer(buffer, np.uint8), begin, length)]
        word = np.repeat(np.arange(len(begin)), length)
        done_sym, done_word = [], []
        none = 1 << 40
        ranks = np.full(len(sym), none, np.int64)
        if len(sym) > 1:
            inside = word[1:] == word[:-1]
            ranks[:-1][inside] = self.rank(sym[:-1][inside], sym[1:][inside])
        while len(sym):
            first = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
            sizes = np.diff(np.append(first, len(sym)))
            best = np.repeat(np.minimum.reduceat(ranks, first), sizes)
            over = best == none
            if over.any():
                done_sym.append(sym[over])
                done_word.append(word[over])
                sym, word, ranks, best = sym[~over], word[~over], ranks[~over], best[~over]
                if not len(sym):
                    break
            hit = np.flatnonzero(ranks == best)
            # Left to right: of neighbouring hits (equal letters) every second one merges.
            run = np.concatenate(([True], np.diff(hit) > 1))
            place = np.arange(len(hit)) - np.maximum.accumulate(np.where(run, np.arange(len(hit)), 0))
            hit = hit[place % 2 == 0]
            sym[hit] = self.merged[ranks[hit]]
            keep = np.ones(len(sym), bool)
            keep[hit + 1] = False
            ranks[hit] = -1
            changed = np.cumsum(keep)[hit] - 1
            sym, word, ranks = sym[keep], word[keep], ranks[keep]
            mark = np.zeros(len(sym), bool)
            mark[changed] = True
            mark[changed[changed > 0] - 1] = True
            touched = np.flatnonzero(mark)
            ranks[touched] = none
            pair = touched[touched + 1 < len(sym)]
            pair = pair[word[pair] == word[pair + 1]]
            ranks[pair] = self.rank(sym[pair], sym[pair + 1])
        if not done_sym:
            return np.zeros(0, np.int64), np.zeros(len(begin), np.int64)
        sym, word = np.concatenate(done_sym), np.concatenate(done_word)
        order = np.argsort(word, kind="stable")
        return sym[order], np.bincount(word, minlength=len(begin))


def compile_lexicon(words: list[bytes], vocabulary: Vocabulary) -> bytes:
    """The minimal acyclic transducer of `words` as one block: header, arcs, ids."""
    words = sorted(set(w for w in words if w))
    register: dict[tuple, int] = {}
    states: list[tuple] = []  # (final, ((byte, state), ...))
    counts: list[int] = []

    def settle(node) -> int:
        key = (node[0], tuple(node[1]))
        if key not in register:
            register[key] = len(states)
            states.append(key)
            counts.append(node[0] + sum(counts[t] for _, t in node[1]))
        return register[key]

    path = [[0, []]]
    last = b""
    for w in words:
        same = 0
        while same < min(len(w), len(last)) and w[same] == last[same]:
            same += 1
        for k in range(len(last), same, -1):
            child = settle(path.pop())
            path[-1][1].append((last[k - 1], child))
        path += [[0, []] for _ in w[same:]]
        path[-1][0] = 1
        last = w
    for k in range(len(last), 0, -1):
        child = settle(path.pop())
        path[-1][1].append((last[k - 1], child))
    root = settle(path.pop())
    arcs = []
    for s, (final, edges) in enumerate(states):
        number = final
        for byte, t in edges:
            arcs.append(((s << 8) | byte, t, number))
            number += counts[t]
    arcs = np.array(sorted(arcs), np.int64).reshape(-1, 3)
    lengths = np.array([len(w) for w in words], np.int64)
    ids, sizes = vocabulary.merge(b"".join(words), np.concatenate(([0], np.cumsum(lengths)))[:-1], lengths) if words else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    final = np.array([f for f, _ in states], np.int64)
    parts = [np.ascontiguousarray(a, "<i8").tobytes() for a in (arcs[:, 0], arcs[:, 1], arcs[:, 2], final, np.concatenate(([0], np.cumsum(sizes))), ids)]
    return struct.pack("<7q", root, *(len(p) for p in parts)) + b"".join(parts)


class Lexicon:
    """A compiled transducer, read through a memory map."""

    def __init__(self, block: bytes | mmap.mmap):
        if isinstance(block, bytes):
            held = mmap.mmap(-1, len(block))
            held.write(block)
            block = held
        self.map = block
        self.root, *sizes = struct.unpack_from("<7q", block)
        at, arrays = 56, []
        for size in sizes:
            arrays.append(np.frombuffer(block, "<i8", size // 8, at))
            at += size
        self.arcs, self.targets, self.outputs, self.final, self.starts, self.ids = arrays

    @classmethod
    def open(cls, path: str) -> Lexicon:
        with open(path, "rb") as f:
            return cls(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ))

    def find(self, buffer: bytes, begin: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Number of each span's word, -1 where the lexicon lacks it."""
        raw = np.frombuffer(buffer, np.uint8)
        out = np.full(len(begin), -1, np.int64)
        if not len(self.arcs):
            return out
        live, state, total = np.arange(len(begin)), np.full(len(begin), self.root, np.int64), np.zeros(len(begin), np.int64)
        step = 0
        while len(live):
            over = length[live] == step
            ended = live[over]
            out[ended] = np.where(self.final[state[over]] == 1, total[over], -1)
            live, state, total = live[~over], state[~over], total[~over]
            if not len(live):
                break
            key = (state << 8) | raw[begin[live] + step]
            at = np.minimum(np.searchsorted(self.arcs, key), len(self.arcs) - 1)
            ok = self.arcs[at] == key
            live, state, total = live[ok], self.targets[at[ok]], total[ok] + self.outputs[at[ok]]
            step += 1
        return out


@dataclass
class Encoder:
    vocabulary: Vocabulary
    lexicon: Lexicon

    def encode(self, texts: list[bytes]) -> list[np.ndarray]:
        """Ids of every text; a special token's string is that token, as in the tokenizer's default."""
        units, owners, lead = [], [], []
        for i, t in enumerate(texts):
            parts = [(None, t)]
            for s, k in self.vocabulary.special.items():
                if s.encode() in t:
                    parts = [(k if n else b, x) for b, p in parts for n, x in enumerate(p.split(s.encode()))]
            for before, p in parts:
                units.append(p)
                owners.append(i)
                lead.append(before)
        got = self._plain(units)
        if len(units) == len(texts):
            return got
        out = [[] for _ in texts]
        for i, before, ids in zip(owners, lead, got):
            out[i] += ([np.array([before])] if before is not None else []) + [ids]
        return [np.concatenate(x) for x in out]

    def _plain(self, texts: list[bytes]) -> list[np.ndarray]:
        out = []
        for group in batches(texts, GROUP):
            buffer, begin, length, firsts = words_of([texts[i] for i in group])
            hashes = span_hashes(buffer, begin, length)
            _, first, inverse = np.unique(hashes, return_index=True, return_inverse=True)
            b, n = begin[first], length[first]
            found = self.lexicon.find(buffer, b, n)
            lacking = np.flatnonzero(found < 0)
            merged, sizes = self.vocabulary.merge(buffer, b[lacking], n[lacking])
            known = np.maximum(found, 0)
            lex = self.lexicon
            start = np.zeros(len(first), np.int64)
            count = np.zeros(len(first), np.int64)
            have = found >= 0
            start[have], count[have] = lex.starts[known[have]], lex.starts[known[have] + 1] - lex.starts[known[have]]
            start[lacking] = len(lex.ids) + np.concatenate(([0], np.cumsum(sizes)))[:-1]
            count[lacking] = sizes
            pool = np.concatenate((lex.ids, merged))
            ids = take_spans(pool, start[inverse], count[inverse])
            ends = np.concatenate(([0], np.cumsum(count[inverse])))[firsts]
            out += [ids[ends[k] : ends[k + 1]] for k in range(len(group))]
        return out

    def decode(self, ids: np.ndarray) -> bytes:
        v = self.vocabulary
        return take_spans(v.flat, v.begins[ids], v.lengths[ids]).tobytes()


def _frequent_rows(capacity: int):
    def run(it):
        names: dict[int, bytes] = {}
        hashes, counts = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        for texts in (utf8(part.column(0)) for batch in it for part in sliced(batch, 0)):
            for group in batches(texts, 4 * PIECE):
                buffer, begin, length, _ = words_of([texts[i] for i in group])
                h, first, n = np.unique(span_hashes(buffer, begin, length), return_index=True, return_counts=True)
                some = n > 1
                h, first, n = h[some], first[some], n[some]
                new = ~np.isin(h, hashes)
                for k, a, size in zip(h[new].tolist(), begin[first[new]].tolist(), length[first[new]].tolist()):
                    names[k] = buffer[a : a + size]
                every = np.concatenate((hashes, h))
                hashes, inverse = np.unique(every, return_inverse=True)
                counts = np.bincount(inverse, np.concatenate((counts, n))).astype(np.int64)
                if len(hashes) > capacity:
                    counts -= np.partition(counts, -capacity)[-capacity]
                    keep = counts > 0
                    hashes, counts = hashes[keep], counts[keep]
                    names = {k: names[k] for k in hashes.tolist()}
        if len(hashes):
            yield pa.RecordBatch.from_arrays([pa.array([names[k] for k in hashes.tolist()], pa.binary()), pa.array(counts)], names=["word", "n"])

    return run


def frequent_words(docs: DataFrame, size: int, capacity: int = 1 << 15) -> list[bytes]:
    """Up to `size` frequent words of all texts (frequencies steer speed only, never ids)."""
    counted = docs.select("text").mapInArrow(trimmed(_frequent_rows(capacity)), "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return [bytes(r["word"]) for r in counted.orderBy(F.desc("n"), "word").limit(size).collect()]


_encoders: dict[bytes, Encoder] = {}


def _encoder(raw: bytes, block: bytes, kinds: bytes) -> Encoder:
    """The encoder of this worker process, which keeps the last one."""
    key = hashlib.sha256(raw + block).digest()
    if key not in _encoders:
        if not _kinds:
            _kinds.append(np.frombuffer(kinds, np.uint8))
        _encoders.clear()
        _encoders[key] = Encoder(Vocabulary(raw), Lexicon(block))
    return _encoders[key]


def encode(docs: DataFrame, vocabulary_file: str, lexicon_size: int = 1 << 14, digests: bool = False) -> DataFrame:
    """The columns of `docs`, then ids array<int> and n_tokens; with `digests`, doc_id, n_tokens and
    SHA-256 of the ids (little-endian 32 bits) and of the decoded text instead.

    Null and empty texts have no ids. Texts of any length are taken whole. Repeated rows are
    encoded each. Columns of `docs` named ids or n_tokens are replaced."""
    with open(vocabulary_file, "rb") as f:
        raw = f.read()
    block = compile_lexicon(frequent_words(docs, lexicon_size), Vocabulary(raw))
    held = docs.sparkSession.sparkContext.broadcast((raw, block, kind_table().tobytes()))
    give_back()
    docs = docs.select("doc_id", "text") if digests else docs.drop("ids", "n_tokens")
    columns = ["doc_id"] if digests else docs.columns
    keep, text = [docs.columns.index(c) for c in columns], docs.columns.index("text")
    names = ["n_tokens", "ids_sha256", "decoded_sha256"] if digests else ["n_tokens", "ids"]

    def run(it):
        encoder = _encoder(*held.value)
        for part in (part for batch in it for part in sliced(batch, text)):
            ids = encoder.encode(utf8(part.column(text)))
            sizes = np.array([len(x) for x in ids], np.int64)
            if digests:
                own = [pa.array([hashlib.sha256(x.astype("<u4").tobytes()).hexdigest() for x in ids]), pa.array([hashlib.sha256(encoder.decode(x)).hexdigest() for x in ids])]
            else:
                own = [pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)), pa.array(np.concatenate(ids).astype(np.int32)))]
            yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keep), pa.array(sizes), *own], names=[*columns, *names])

    fields = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    if not digests:
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields) + ", n_tokens long, ids array<int>"
    return docs.mapInArrow(trimmed(run), fields)
