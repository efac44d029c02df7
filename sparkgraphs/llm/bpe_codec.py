"""BPE encoding and decoding over a minimal acyclic transducer of frequent words.

A pass over the whole corpus counts white-space chunks (lossy per task: a task drops chunks it saw fewer than `least` times,
which can only keep a word out of the lexicon). The frequent words are compiled on the driver, with the ids that exact merging
gives them, into a minimal acyclic automaton whose arcs carry integer outputs: their sum along a word is the word's number, which
addresses its ids. Workers memory-map the automaton; words outside it are merged exactly. Results never depend on the lexicon.
The new words of a run of texts take each step of the automaton, and each merge, together.

Defined cases: null and empty texts encode to no ids and decode to the empty text; texts of any length are encoded whole; special
strings inside texts become their special ids; repeated rows are encoded row by row; empty tables give empty results; extra
columns of the input are ignored.
"""

from __future__ import annotations

import hashlib
import json
import mmap
import os
import struct
import tempfile
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain, filterfalse, repeat

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, map_arrow, table
from .token_counts import MEMO_ENTRIES, byte_symbols, merges_left

LEXICON_WORDS = 32_768
#: Words of up to so many bytes are merged without a heap.
SHORT = 24
#: About so many chunks are looked at before their new words are merged together.
RUN = 1 << 16
#: Letters below are the same in every version of Unicode.
LATIN_END = "\u0250"
#: The byte strings of one byte.
ONE = [bytes([b]) for b in range(256)]
#: The byte-level split of this vocabulary family (fixed value of the tokenizer format).
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def merged_short(symbols: list[str], rank: dict[tuple[str, str], int]) -> list[str]:
    """The same merges as with a heap: for a short word looking for the lowest rank costs less than keeping one."""
    none, get = len(rank), rank.get
    ranks = list(map(get, zip(symbols, symbols[1:]), repeat(none)))
    while ranks and (low := min(ranks)) < none:
        i = ranks.index(low)
        symbols[i] += symbols[i + 1]
        del symbols[i + 1], ranks[i]
        if i:
            ranks[i - 1] = get((symbols[i - 1], symbols[i]), none)
        if i < len(ranks):
            ranks[i] = get((symbols[i], symbols[i + 1]), none)
    return symbols


class ByteBpe:
    """Exact merging of a byte-level vocabulary with the special strings of the file."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        self.vocab: dict[str, int] = spec["model"]["vocab"]
        self.rank = {(a, b): i for i, (a, b) in enumerate(m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])}
        self.names = {w: str(i) for w, i in self.vocab.items()}
        self.symbols = byte_symbols()
        back = {s: b for b, s in enumerate(self.symbols)}
        self.pieces = {str(i): bytes(back[c] for c in w) for w, i in self.vocab.items() if all(c in back for c in w)}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.pieces |= {str(i): s.encode() for s, i in self.special.items()}
        self.special_split = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.split = regex.compile(SPLIT)
        self.of_byte = np.array([self.vocab[s] for s in self.symbols])
        self.texts = {i: t for i, t in zip(self.vocab.values(), self.names.values(), strict=True)}
        pairs = np.array([self._pair(self.vocab[a], self.vocab[b]) for a, b in self.rank], np.int64)
        #: Sorted pairs with the rank of each, and by rank the id that a pair becomes.
        self.order = np.argsort(pairs)
        self.pairs = pairs[self.order]
        self.made = np.array([self.vocab[a + b] for a, b in self.rank], np.int64)
        self.first_ranks = self._ranks(self.of_byte[:, None], self.of_byte[None, :])

    @staticmethod
    def _pair(left, right):
        return left << 32 | right

    def _ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The rank of each pair of ids, or the number of ranks for those that do not merge."""
        none, pair = len(self.made), self._pair(left, right)
        if not none:
            return np.zeros(pair.shape, np.int64)
        at = np.minimum(np.searchsorted(self.pairs, pair), none - 1)
        return np.where(self.pairs[at] == pair, self.order[at], none)

    def merged_together(self, data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Words as numbers of places in `starts`, with their ids as a row of a matrix: all words of a number of symbols take one merge at a time.

        Word i is `data[starts[i] : starts[i] + sizes[i]]`. A word with a merge left has one symbol less after it, so it goes on with
        the words of that length; the others are done.
        """
        none = len(self.made)
        words, ids, ranks = np.zeros(0, np.int64), np.zeros((0, 0), np.int64), np.zeros((0, 0), np.int64)
        for size in range(int(sizes.max(initial=0)), 0, -1):
            new = np.flatnonzero(sizes == size)
            raw = data[starts[new][:, None] + np.arange(size)]
            words = np.concatenate([words, new])
            ids = np.concatenate([ids.reshape(len(ids), size), self.of_byte[raw]])
            ranks = np.concatenate([ranks.reshape(len(ranks), size - 1), self.first_ranks[raw[:, :-1], raw[:, 1:]]])
            if size == 1:
                yield words, ids
                return
            at = ranks.argmin(axis=1)
            low = ranks[np.arange(len(words)), at]
            open_ = low < none
            yield words[~open_], ids[~open_]
            words, ids, ranks, at, low = words[open_], ids[open_], ranks[open_], at[open_], low[open_]
            rows = np.arange(len(words))
            ids[rows, at] = self.made[low]
            ids = ids[np.arange(size) != at[:, None] + 1].reshape(len(words), size - 1)
            ranks = ranks[np.arange(size - 1) != at[:, None]].reshape(len(words), size - 2)
            for near, side in ((rows[at > 0], at[at > 0] - 1), (rows[at < size - 2], at[at < size - 2])):
                ranks[near, side] = self._ranks(ids[near, side], ids[near, side + 1])

    def merged(self, word: bytes) -> list[str]:
        symbols = list(map(self.symbols.__getitem__, word))
        return merged_short(symbols, self.rank) if len(symbols) <= SHORT else merges_left(symbols, self.rank)

    def merge(self, word: str) -> list[int]:
        return [self.vocab[s] for s in self.merged(word.encode("utf-8"))]


@lru_cache(maxsize=1)
def byte_bpe(path: str) -> ByteBpe:
    """The vocabulary of `path`, read once by a worker that runs many tasks."""
    return ByteBpe(path)


def compile_lexicon(entries: dict[str, list[int]]) -> bytes:
    """The minimal acyclic transducer of `entries`, laid out for memory mapping.

    Words are added in byte order; when a word's suffix is complete its states are replaced by equal ones met before, so that
    suffixes are shared. Arcs then get as output the number of words that sort before those under them.
    """
    words = sorted((w.encode("utf-8"), ids) for w, ids in entries.items() if w)
    known: dict[tuple, int] = {}
    states: list[tuple[bool, tuple[tuple[int, int], ...]]] = []

    def settle(node: list) -> int:
        sign = (node[0], tuple(node[1]))
        if sign not in known:
            known[sign] = len(states)
            states.append(sign)
        return known[sign]

    path: list[list] = [[False, []]]
    last = b""

    def close(to: int) -> None:
        while len(path) - 1 > to:
            done = settle(path.pop())
            path[-1][1].append((last[len(path) - 1], done))

    for word, _ in words:
        same = len(os.path.commonprefix([last, word]))
        close(same)
        path.extend([False, []] for _ in word[same:])
        path[-1][0] = True
        last = word
    close(0)
    root = settle(path[0])
    below = [0] * len(states)
    for s, (final, arcs) in enumerate(states):  # targets are settled before their sources
        below[s] = final + sum(below[t] for _, t in arcs)
    first, labels, targets, outputs = [], bytearray(), [], []
    for final, arcs in states:
        first.append(len(labels))
        ahead = int(final)
        for label, t in arcs:
            labels.append(label)
            targets.append(t)
            outputs.append(ahead)
            ahead += below[t]
    first.append(len(labels))
    starts, flat = [0], []
    for _, ids in words:
        flat += ids
        starts.append(len(flat))
    finals = bytes(f for f, _ in states)
    head = struct.pack("<5q", root, len(states), len(labels), len(starts), len(flat))
    ints = [first, targets, outputs, starts, flat]
    return head + b"".join(struct.pack(f"<{len(x)}i", *x) for x in ints) + finals + bytes(labels)


class MappedLexicon:
    """A compiled lexicon read through a memory map; its file is unlinked at once, so nothing stays behind."""

    def __init__(self, blob: bytes):
        with tempfile.TemporaryFile() as f:
            f.write(blob)
            f.flush()
            self.map = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        self.root, n_states, n_arcs, n_starts, n_flat = struct.unpack_from("<5q", self.map)
        view, at = memoryview(self.map), 40
        parts = []
        for n in (n_states + 1, n_arcs, n_arcs, n_starts, n_flat):
            parts.append(view[at : at + 4 * n].cast("i"))
            at += 4 * n
        self.first, self.targets, self.outputs, self.starts, self.flat = parts
        self.finals, self.labels, self.n_states, self.n_words = at, at + n_states, n_states, n_starts - 1
        #: For steps of many words together: arcs in order of source and label, as they are laid out.
        self.arcs = np.repeat(np.arange(n_states) << 8, np.diff(np.asarray(self.first))) | np.frombuffer(self.map, np.uint8, n_arcs, self.labels)
        self.arc_targets, self.arc_outputs = np.asarray(self.targets), np.asarray(self.outputs)
        self.final = np.frombuffer(self.map, np.uint8, n_states, self.finals)

    def ids(self, word: bytes) -> list[int] | None:
        state, number, first, labels, find = self.root, 0, self.first, self.labels, self.map.find
        outputs, targets = self.outputs, self.targets
        for label in map(ONE.__getitem__, word):
            arc = find(label, labels + first[state], labels + first[state + 1]) - labels
            if arc < 0:
                return None
            number += outputs[arc]
            state = targets[arc]
        if not self.map[self.finals + state]:
            return None
        return self.flat[self.starts[number] : self.starts[number + 1]].tolist()

    def numbers(self, data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """The number of each word `data[starts[i] : starts[i] + sizes[i]]`, or -1: all words take a step of the automaton together."""
        number = np.full(len(starts), -1, np.int64)
        live, state, sums, step = np.arange(len(starts)), np.full(len(starts), self.root), np.zeros(len(starts), np.int64), 0
        while live.size:
            ended = sizes[live] == step
            done = ended & (self.final[state] > 0)
            number[live[done]] = sums[done]
            live, state, sums = live[~ended], state[~ended], sums[~ended]
            key = state << 8 | data[starts[live] + step]
            arc = np.searchsorted(self.arcs, key)
            found = np.flatnonzero(arc < len(self.arcs))
            found = found[self.arcs[arc[found]] == key[found]]
            arc = arc[found]
            live, state, sums, step = live[found], self.arc_targets[arc].astype(np.int64), sums[found] + self.arc_outputs[arc], step + 1
        return number


def one_word(chunk: str) -> bool:
    """Whether a chunk is letters alone, so that no split is needed; letters of later blocks are left to the split."""
    return chunk.isalpha() and (chunk.isascii() or max(chunk) < LATIN_END)


class Codec:
    """Encodes to decimal ids joined by commas, and decodes them."""

    def __init__(self, path: str, lexicon: bytes, entries: int = MEMO_ENTRIES):
        self.bpe, self.lexicon, self.entries = byte_bpe(path), MappedLexicon(lexicon), entries
        self.words: dict[str, str] = {}
        self.inner: dict[str, str] = {}
        self.special = {s: str(i) for s, i in self.bpe.special.items()}

    def _merged(self, words: list[str]) -> list[str]:
        """The ids of each word, from the lexicon or by merging."""
        raw = [w.encode("utf-8") for w in words]
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        data, starts = np.frombuffer(b"".join(raw), np.uint8), np.cumsum(sizes) - sizes
        out = [""] * len(words)
        numbers = self.lexicon.numbers(data, starts, sizes)
        for i in np.flatnonzero(numbers >= 0).tolist():
            n = int(numbers[i])
            out[i] = ",".join(map(str, self.lexicon.flat[self.lexicon.starts[n] : self.lexicon.starts[n + 1]].tolist()))
        for i in np.flatnonzero((numbers < 0) & (sizes > SHORT)).tolist():
            out[i] = ",".join(map(self.bpe.names.__getitem__, self.bpe.merged(raw[i])))
        left = np.flatnonzero((numbers < 0) & (sizes <= SHORT))
        text = self.bpe.texts.__getitem__
        for places, ids in self.bpe.merged_together(data, starts[left], sizes[left]):
            for i, row in zip(left[places].tolist(), ids.tolist(), strict=True):
                out[i] = ",".join(map(text, row))
        return out

    def _cut(self, text: str) -> Iterator[tuple[dict[str, str], list[str]]]:
        """The text as words, then chunks after a blank.

        Blanks between two non-blank characters always start a word, so chunks between them are encoded on their own. If a chunk
        starts or ends with white space, or is empty, it is not cut off rightly at its blank: all are words then.
        """
        if not text:
            return
        head, *rest = text.split(" ")
        new = [head, *filterfalse(self.inner.__contains__, rest)]
        if rest and all(new) and new == list(map(str.strip, new)):
            yield self.words, self.bpe.split.findall(head)
            yield self.inner, rest
        else:
            yield self.words, self.bpe.split.findall(text)

    def _pieces(self, text: str) -> Iterator[tuple[dict[str, str], list[str]]]:
        if self.bpe.special_split and any(s in text for s in self.bpe.special):
            for i, part in enumerate(self.bpe.special_split.split(text)):
                if i % 2:
                    yield self.special, [part]
                else:
                    yield from self._cut(part)
        else:
            yield from self._cut(text)

    def _learn(self, held: list[tuple[int, dict[str, str], list[str]]]) -> None:
        """Puts into the memos what they lack; they start anew when full."""
        for memo in (self.words, self.inner):
            if len(memo) >= self.entries:
                memo.clear()
        new: dict[int, set[str]] = {id(self.words): set(), id(self.inner): set(), id(self.special): set()}
        for _, memo, keys in held:
            new[id(memo)].update(filterfalse(memo.__contains__, keys))
        chunks = new[id(self.inner)]
        whole = [c for c in chunks if one_word(c)]
        chunks.difference_update(whole)
        mixed, blanked = list(chunks), [" " + c for c in whole]
        cut = [self.bpe.split.findall(" " + c) for c in mixed]
        words = list(new[id(self.words)].union(filterfalse(self.words.__contains__, chain(blanked, *cut))))
        self.words.update(zip(words, self._merged(words), strict=True))
        text = self.words.__getitem__
        self.inner.update(zip(whole, map(text, blanked), strict=True))
        self.inner.update((c, ",".join(map(text, found))) for c, found in zip(mixed, cut, strict=True))

    def encode_all(self, texts: list[str | None]) -> list[str]:
        out: list[list[str]] = [[] for _ in texts]
        held: list[tuple[int, dict[str, str], list[str]]] = []
        size = 0

        def flush() -> None:
            self._learn(held)
            for place, memo, keys in held:
                out[place].append(",".join(map(memo.__getitem__, keys)))
            held.clear()

        for place, text in enumerate(texts):
            for memo, keys in self._pieces(text or ""):
                for at in range(0, len(keys), RUN):  # a very long text is learnt by runs too
                    held.append((place, memo, keys[at : at + RUN]))
                    size += len(held[-1][2])
                    if size >= RUN:
                        flush()
                        size = 0
        flush()
        return list(map(",".join, out))

    def encode(self, text: str | None) -> str:
        return self.encode_all([text])[0]

    def decode(self, ids: str) -> str:
        return b"".join(map(self.bpe.pieces.__getitem__, ids.split(","))).decode("utf-8", "replace") if ids else ""


def frequent_words(docs: DataFrame, *, text: str = "text", words: int = LEXICON_WORDS, least: int = 3, held: int = 1 << 19) -> list[str]:
    """The commonest pre-tokens of all texts, at most `words` of them, for the lexicon."""
    bounded_batches(docs.sparkSession)
    split = SPLIT

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for b in batches:
            for t in b.column(0).to_pylist():
                if t:
                    seen.update(t.split(" "))
            if len(seen) > held:  # lossy counting: what is rare so far goes
                seen = Counter({w: n for w, n in seen.items() if n >= least})
        cut = regex.compile(split)
        out: Counter = Counter()
        for chunk, n in seen.items():
            if n >= least and chunk:
                for w in cut.findall(" " + chunk):
                    out[w] += n
        most = out.most_common(4 * words)
        yield pa.RecordBatch.from_arrays([pa.array([w for w, _ in most], pa.string()), pa.array([n for _, n in most], pa.int64())], names=["word", "n"])

    counts = map_arrow(docs.select(text), body, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return [r.word for r in counts.orderBy(F.desc("n"), "word").limit(words).collect()]


def build_lexicon(words: list[str], tokenizer: str) -> bytes:
    bpe = byte_bpe(tokenizer)
    return compile_lexicon({w: bpe.merge(w) for w in words})


def encode_decode(docs: DataFrame, tokenizer: str, *, text: str = "text", lexicon: bytes | None = None, lexicon_words: int = LEXICON_WORDS, digests: bool = False, entries: int = MEMO_ENTRIES) -> DataFrame:
    """All columns of `docs` with bpe_ids (array of int) and bpe_text (their decoding); `digests`: with n_tokens, ids_sha256 and decoded_sha256 instead."""
    spark = docs.sparkSession
    blob = spark.sparkContext.broadcast(lexicon if lexicon is not None else build_lexicon(frequent_words(docs, text=text, words=lexicon_words), tokenizer))
    bounded_batches(spark)

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(tokenizer, blob.value, entries)
        for b in batches:
            ids = codec.encode_all(b.column(text).to_pylist())
            back = map(codec.decode, ids)
            if digests:
                new = {
                    "n_tokens": pa.array([x.count(",") + 1 if x else 0 for x in ids], pa.int64()),
                    "ids_sha256": pa.array([hashlib.sha256(x.encode()).hexdigest() for x in ids], pa.string()),
                    "decoded_sha256": pa.array([hashlib.sha256(x.encode("utf-8")).hexdigest() for x in back], pa.string()),
                }
            else:
                parts = [np.fromstring(x, np.int32, sep=",") if x else np.zeros(0, np.int32) for x in ids]
                offsets = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int32))
                new = {"bpe_ids": pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([np.zeros(0, np.int32), *parts]))), "bpe_text": pa.array(list(back), pa.string())}
            kept = [(n, c) for n, c in zip(b.schema.names, b.columns, strict=True) if not digests or n != text]
            yield pa.RecordBatch.from_arrays([c for _, c in kept] + list(new.values()), names=[n for n, _ in kept] + list(new))

    clash = {"bpe_ids", "bpe_text", "n_tokens", "ids_sha256", "decoded_sha256"} & set(docs.columns)
    slim = docs.drop(*clash)
    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in slim.schema if not digests or f.name != text]
    fields += ["n_tokens long", "ids_sha256 string", "decoded_sha256 string"] if digests else ["bpe_ids array<int>", "bpe_text string"]
    return map_arrow(slim, body, ", ".join(fields))


def op8_bpe_encode_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return encode_decode(docs, public_tokenizers.path("byte_bpe_50k.json"), digests=True)
