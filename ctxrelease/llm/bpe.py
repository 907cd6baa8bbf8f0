"""Byte-pair encoding and decoding through a minimal acyclic transducer.

Frequent words of the corpus are compiled into an automaton that shares prefixes and suffixes; each edge
carries a number, and the numbers on a word's path add up to the word's place in the list of id sequences.
The compiled automaton is one flat file that every executor maps into memory. Words that it lacks are merged
exactly, many at a time. Decoding joins token strings with blanks, as the vocabulary file prescribes.

Nulls and empty texts have no ids. Texts with characters outside the plain Latin range go through the
vocabulary file's own normaliser and splitter, then through the same automaton and merges.
"""

from __future__ import annotations

import atexit
import hashlib
import json
import os
import re
import shutil
import tempfile
import unicodedata
import uuid
from collections import Counter
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import append_columns, claim, give_back, on_drop, remembered, slices, text_slices

#: Words in the automaton, by falling count; the list is bounded, so the file is too (some 5 MB).
LEXICON_WORDS = 131_072
#: Longer words (in UTF-8 bytes) are left to the merges.
LEXICON_WORD_BYTES = 40
#: Chunks whose encoding a process remembers as Arrow columns, and their longest; half of them go when there are more.
MEMO_CHUNKS, MEMO_CHUNK_BYTES = 400_000, 40
#: Words of texts outside the plain range that it remembers in each of two generations; the older one goes when the newer is full.
MEMO_WORDS = 40_000
#: Characters of the texts that are encoded at a time.
TEXT_SLICE = 3 << 20
#: Words that a task counts before it hands them on.
COUNT_WORDS = 200_000
NO_RANK = np.int32(1 << 30)

_WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")
_ASCII_WORDS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\sa-z0-9]+")
#: White space to str.split(), but not to the vocabulary file.
_ODD_SPACE = "\x1c\x1d\x1e\x1f"
_PLAIN = re.compile(r"[\t-\r\x20-\x7e\xa1-ſ–—‘’“”…€]*")
# the plain range's letters and numbers, for the same words as _WORDS by the faster matcher
_LETTERS = "a-z" + "".join(chr(c) for c in range(0xA1, 0x180) if unicodedata.category(chr(c))[0] == "L")
_NUMBERS = "0-9" + "".join(chr(c) for c in range(0xA1, 0x180) if unicodedata.category(chr(c))[0] == "N")
_FORM = rf"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[{_NUMBERS}]|[^\s{_LETTERS}{_NUMBERS}]+"
_PLAIN_WORDS, _LINE_WORDS = re.compile(_FORM), re.compile(_FORM + r"|\n")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Vocabulary:
    """Ids, merge ranks and token strings of a vocabulary file with word ends."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            content = json.load(f)
        ids: dict[str, int] = content["model"]["vocab"]
        suffix = content["model"]["end_of_word_suffix"] or ""
        self.path = path
        self.special = {t["content"]: t["id"] for t in content["added_tokens"]}
        self.tokens = [""] * (max([*ids.values(), *self.special.values()]) + 1)
        for token, i in [*ids.items(), *self.special.items()]:
            self.tokens[i] = token
        self.token_bytes = [t.encode() for t in self.tokens]
        shown = byte_alphabet()
        self.inner = np.array([ids[shown[b]] for b in range(256)], np.int32)
        self.last = np.array([ids[shown[b] + suffix] for b in range(256)], np.int32)
        left, right, made = [], [], []
        for a, b in content["model"]["merges"]:
            left.append(ids[a])
            right.append(ids[b])
            made.append(ids[a + b])
        keys = (np.array(left, np.int64) << 32) | np.array(right, np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank, self.made = keys[order], order.astype(np.int32), np.array(made, np.int32)
        # ranks of the first round's pairs by their two bytes: within a word, and at its end
        self.first = [self.ranks(np.repeat(self.inner, 256), np.tile(x, 256)) for x in (self.inner, self.last)]
        self.split_special = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.back = {c: b for b, c in enumerate(shown)}
        self._steps = None

    def library(self):
        """The library's tokenizer of the file, for comparisons."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def own_split(self, text: str) -> list[tuple[str, tuple[int, int]]]:
        """The file's own normaliser and splitter; they are kept without the library's model, which takes far more memory."""
        if self._steps is None:
            whole = self.library()
            self._steps = whole.normalizer, whole.pre_tokenizer
        normalizer, splitter = self._steps
        return splitter.pre_tokenize_str(normalizer.normalize_str(text))

    def ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of merging each pair; NO_RANK where there is none, as with -1 for no id. A rank's result is in `made`."""
        key = (a.astype(np.int64) << 32) | b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.rank[at], NO_RANK)

    def merge(self, words: list[bytes]) -> list[bytes]:
        """Ids of words, 4 bytes each: in each round every word merges its best-ranked leftmost pair."""
        out: list[bytes] = [b""] * len(words)
        lens = np.fromiter(map(len, words), np.int64, len(words))
        flat, start = np.frombuffer(b"".join(words), np.uint8), np.cumsum(lens) - lens
        order = np.argsort(lens, kind="stable")
        rising = lens[order]
        at = int(np.searchsorted(rising, 0, "right"))
        while at < len(order):
            end = min(at + 4096, int(np.searchsorted(rising, max(16, rising[at] * 5 // 4), "right")))
            some = order[at:end]
            cols = np.arange(rising[end - 1])
            ids = self._merge_block(flat[np.minimum(start[some, None] + cols, len(flat) - 1)], lens[some])
            kept = ids >= 0
            joined, first = ids[kept].astype("<u4").tobytes(), 0
            for place, last in zip(some.tolist(), (4 * kept.sum(1).cumsum()).tolist()):
                out[place] = joined[first:last]
                first = last
            at = end
        return out

    def _merge_block(self, raw: np.ndarray, lens: np.ndarray) -> np.ndarray:
        """Ids by row, then -1, of words whose bytes fill their rows up to `lens`; as each round takes one id of every row
        that goes on, the rows narrow by one."""
        n, width = raw.shape
        rows, cols = np.arange(n), np.arange(width)
        ids = self.inner[raw]
        ids[rows, lens - 1] = self.last[raw[rows, lens - 1]]
        ids[cols >= lens[:, None]] = -1
        out = np.full((n, width), -1, np.int32)
        two = raw[:, :-1].astype(np.int32) * 256 + raw[:, 1:]
        rank = self.first[0][two]
        rank[cols[1:] >= lens[:, None]] = NO_RANK
        ends = rows[lens > 1]
        rank[ends, lens[ends] - 2] = self.first[1][two[ends, lens[ends] - 2]]
        while ids.shape[1] > 1:
            width = ids.shape[1]
            best = rank.argmin(1)
            low = rank[np.arange(len(rows)), best]
            going = low < NO_RANK
            if not going.all():
                out[rows[~going], :width] = ids[~going]
                rows, ids, rank, best, low = (x[going] for x in (rows, ids, rank, best, low))
            k = np.arange(len(rows))
            after = cols[: width - 1] > best[:, None]
            ids = np.where(after, ids[:, 1:], ids[:, :-1])
            ids[k, best] = self.made[low]
            if width > 2:
                rank = np.where(after[:, :-1], rank[:, 1:], rank[:, :-1])
                left, right = np.flatnonzero(best > 0), np.flatnonzero(best < width - 2)
                pair = np.concatenate([best[left] - 1, best[right]])
                k = np.concatenate([left, right])
                rank[k, pair] = self.ranks(ids[k, pair], ids[k, pair + 1])
        out[rows, : ids.shape[1]] = ids
        return out


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte: itself if printable Latin-1, else the next free one from U+0100."""
    own = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    free = iter(range(0x100, 0x200))
    return [chr(b) if b in own else chr(next(free)) for b in range(256)]


@lru_cache(maxsize=4)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def pieces(voc: Vocabulary, text: str) -> list[str]:
    """Words of a text in the order of the vocabulary file's splitter; special tokens stay whole."""
    if voc.split_special and "<|" in text and voc.split_special.search(text):
        parts = voc.split_special.split(text)
        return [w for k, part in enumerate(parts) for w in ([part] if k % 2 else _words(voc, part))]
    return _words(voc, text)


def words_of(voc: Vocabulary, text: str) -> list[str]:
    """Words of a whole text: in one pass if it is plain, else chunk by chunk between white space, which no word crosses."""
    if "<|" in text or any(c in text for c in _ODD_SPACE):
        return pieces(voc, text)
    if _PLAIN.fullmatch(text):
        return _words(voc, text)
    return [w for chunk in text.split() for w in _words(voc, chunk)]


def _words(voc: Vocabulary, text: str) -> list[str]:
    if _PLAIN.fullmatch(text):
        if text.isascii():
            return _ASCII_WORDS.findall(text.lower())
        low = unicodedata.normalize("NFC", text).lower()
        return _PLAIN_WORDS.findall(low) if _PLAIN.fullmatch(low) else _WORDS.findall(low)
    found = voc.own_split(text) if text else []
    return [bytes(voc.back[c] for c in w).decode() for w, _ in found]


class Lexicon:
    """The compiled automaton over a memory-mapped file.

    Sections, as little-endian arrays: edge keys (state * 256 + byte, sorted), edge targets, edge numbers,
    final flags by state, offsets of id sequences, ids.
    """

    PARTS = ("keys", "target", "number", "final", "offset", "ids")

    def __init__(self, path: str):
        raw = np.memmap(path, np.int64, "r")
        at = 1 + len(self.PARTS)
        for k, name in enumerate(self.PARTS):
            size = int(raw[1 + k])
            setattr(self, name, raw[at : at + size])
            at += size

    def find(self, words: list[bytes]) -> np.ndarray:
        """The number of each word, or -1; all words step in parallel."""
        n = len(words)
        out = np.full(n, -1, np.int64)
        if not n or not len(self.keys):
            return out
        lens = np.array([len(w) for w in words])
        width = int(min(lens.max(), LEXICON_WORD_BYTES))
        raw = np.frombuffer(b"".join(w[:width].ljust(width, b"\0") for w in words), np.uint8).reshape(n, width).astype(np.int64)
        live = np.flatnonzero((lens <= width) & (lens > 0))
        state, number = np.zeros(n, np.int64), np.zeros(n, np.int64)
        for step in range(width):
            done = live[lens[live] == step]
            out[done] = np.where(self.final[state[done]] > 0, number[done], -1)
            live = live[lens[live] > step]
            if not len(live):
                break
            key = state[live] * 256 + raw[live, step]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            hit = self.keys[at] == key
            live, at = live[hit], at[hit]
            state[live] = self.target[at]
            number[live] += self.number[at]
        done = live[lens[live] == width]
        out[done] = np.where(self.final[state[done]] > 0, number[done], -1)
        return out


def compile_lexicon(words: list[bytes], encode: Callable[[list[bytes]], list[bytes]], path: str) -> int:
    """Writes the minimal automaton of the distinct `words`; returns its number of states."""
    words = sorted({w for w in words if 0 < len(w) <= LEXICON_WORD_BYTES})
    known: dict[tuple, int] = {}
    states: list[tuple] = []

    def settle(node: list) -> int:
        key = (node[0], *node[1])
        at = known.get(key)
        if at is None:
            at = known[key] = len(states)
            states.append(key)
        return at

    # the path of the last word: [is final, [(byte, state), ...], byte that leads here]
    path_nodes: list[list] = [[False, [], 0]]
    last = b""
    for word in words:
        same = 0
        limit = min(len(word), len(last))
        while same < limit and word[same] == last[same]:
            same += 1
        while len(path_nodes) > same + 1:
            node = path_nodes.pop()
            path_nodes[-1][1].append((node[2], settle(node)))
        for b in word[same:]:
            path_nodes.append([False, [], b])
        path_nodes[-1][0] = True
        last = word
    while len(path_nodes) > 1:
        node = path_nodes.pop()
        path_nodes[-1][1].append((node[2], settle(node)))
    root = settle(path_nodes[0])
    below = [0] * len(states)
    for i, (final, *edges) in enumerate(states):  # children settle before their parents
        below[i] = int(final) + sum(below[s] for _, s in edges)
    new = {root: 0} | {s: k + 1 for k, s in enumerate(i for i in range(len(states)) if i != root)}
    rows = []
    for i, (final, *edges) in enumerate(states):
        before = int(final)
        for b, s in edges:
            rows.append((new[i] * 256 + b, new[s], before))
            before += below[s]
    rows.sort()
    table = np.array(rows, np.int64).reshape(-1, 3)
    final = np.zeros(len(states), np.int64)
    for i, (is_final, *_) in enumerate(states):
        final[new[i]] = is_final
    ids = [np.frombuffer(x, "<u4") for x in encode(words)]
    offset = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int64)
    sections = [table[:, 0], table[:, 1], table[:, 2], final, offset, np.concatenate([np.zeros(0, np.int64), *ids]).astype(np.int64)]
    with open(path, "wb") as f:
        np.array([1, *map(len, sections)], np.int64).tofile(f)
        for s in sections:
            np.ascontiguousarray(s).tofile(f)
    return len(states)


@lru_cache(maxsize=2)
def mapped(name: str) -> Lexicon:
    return Lexicon(SparkFiles.get(name))


on_drop("bpe", vocabulary.cache_clear)
on_drop("bpe", mapped.cache_clear)


class Memory:
    """Remembered values of a bounded number of keys in two generations: what is asked for moves to the newer one, so
    frequent keys outlive the rare ones that fill it."""

    def __init__(self, make: Callable[[list[str]], list], most: int = MEMO_WORDS):
        self.make, self.most = make, most
        self.new: dict[str, object] = {}
        self.old: dict[str, object] = {}

    def of(self, keys: list[str]) -> list:
        """Values of keys that may repeat."""
        missing = set(keys).difference(self.new)
        if missing:
            if len(self.new) + len(missing) > self.most:
                self.old, self.new = self.new, {}
                missing = set(keys)
            known = missing.intersection(self.old)
            self.new.update(zip(known, map(self.old.__getitem__, known)))
            unseen = list(missing.difference(known))
            self.new.update(zip(unseen, self.make(unseen)))
        return list(map(self.new.__getitem__, keys))


class Chunks:
    """Remembered encodings of a bounded number of chunks, in Arrow columns; those that were asked for last stay."""

    def __init__(self, make: Callable[[pa.Array], list[pa.Array]], sides: int, most: int = MEMO_CHUNKS):
        self.make, self.most, self.turn = make, most, 0
        self.keys, self.used = pa.array([], pa.string()), np.zeros(0, np.int64)
        self.sides = [pa.array([], pa.binary())] * sides

    def of(self, chunks: pa.Array) -> tuple[np.ndarray, list[pa.Array]]:
        """The place of each of some distinct chunks, and the columns that hold their values there."""
        self.turn += 1
        found = pc.index_in(chunks, value_set=self.keys)
        missing = chunks.filter(found.is_null())
        known = len(self.keys)
        place = found.fill_null(-1).to_numpy()
        self.used[place[place >= 0]] = self.turn
        if not len(missing):
            return place, self.sides
        place = place.copy()
        place[place < 0] = known + np.arange(len(missing))
        made = self.make(missing)
        whole = [pa.concat_arrays([x, y]) for x, y in zip(self.sides, made)]
        short = np.flatnonzero(pc.binary_length(missing).to_numpy() <= MEMO_CHUNK_BYTES)
        kept = np.concatenate([np.arange(known), known + short])
        used = np.concatenate([self.used, np.full(len(short), self.turn)])
        if len(kept) > self.most:
            last = np.sort(np.argsort(-used, kind="stable")[: self.most // 2])
            kept, used = kept[last], used[last]
        keys = pa.concat_arrays([self.keys, missing])
        all_stay = len(kept) == len(keys)
        self.keys, self.used = keys if all_stay else keys.take(pa.array(kept)), used
        self.sides = whole if all_stay else [x.take(pa.array(kept)) for x in whole]
        return place, whole


class Encoder:
    """Encodes whole texts: chunks between white space, which no word crosses, are parted, numbered and put together as
    Arrow columns; only the words of a slice's distinct chunks that aren't remembered are looked up one by one.

    Words come from the automaton or, unseen, from the merges. With `decoded`, the token strings come along, each after a blank.
    """

    def __init__(self, voc: Vocabulary, lexicon: Lexicon | None = None, decoded: bool = False):
        self.voc, self.lexicon, self.decoded = voc, lexicon, decoded
        self.words = Memory(self.encode_words)
        self.chunks = Chunks(self.encode_chunks, 1 + decoded)

    def encode_words(self, words: list[str]) -> list:
        """Ids of distinct words, 4 bytes each; with their token strings, if `decoded`."""
        out: list[bytes] = [b""] * len(words)
        special = self.voc.special
        for k, w in enumerate(words):
            if w in special:
                out[k] = np.array([special[w]], "<u4").tobytes()
        rest = [k for k, x in enumerate(out) if not x and words[k] != "\n"]
        raw = [words[k].encode() for k in rest]
        if self.lexicon is not None and rest:
            number = self.lexicon.find(raw)
            hit = np.flatnonzero(number >= 0)
            a, b = self.lexicon.offset[number[hit]].tolist(), self.lexicon.offset[number[hit] + 1].tolist()
            for at, i, j in zip(hit.tolist(), a, b):
                out[rest[at]] = self.lexicon.ids[i:j].astype("<u4").tobytes()
            left = np.flatnonzero(number < 0).tolist()
            rest, raw = [rest[at] for at in left], [raw[at] for at in left]
        for k, ids in zip(rest, self.voc.merge(raw)):
            out[k] = ids
        if not self.decoded:
            return out
        tokens = self.voc.token_bytes
        return [(x, b"".join([b" " + tokens[i] for i in np.frombuffer(x, "<u4").tolist()])) for x in out]

    def _parted(self, found: list) -> list[list[bytes]]:
        """What encode_words gives, as one list of ids and, if wanted, one of token strings."""
        return [list(x) for x in zip(*found)] or [[], []] if self.decoded else [found]

    def encode_chunks(self, chunks: pa.Array) -> list[pa.Array]:
        """A column of the ids of plain chunks; with one of their token strings, if `decoded`."""
        lines = pc.binary_join(pa.ListArray.from_arrays([0, len(chunks)], chunks), "\n")[0].as_py()
        words = _LINE_WORDS.findall(f"{lines}\n")  # a line end closes each chunk
        closed = np.array([0, *(k + 1 for k, w in enumerate(words) if w == "\n")], np.int64)
        distinct = list(set(words))
        known = dict(zip(distinct, self.encode_words(distinct)))
        out = []
        for values in self._parted([known[w] for w in words]):
            # the chunks' bytes lie one after another
            flat = pa.array(values, pa.binary())
            ends = np.frombuffer(flat.buffers()[1], np.int32, len(flat) + 1)[closed]
            out.append(pa.Array.from_buffers(pa.binary(), len(chunks), [None, pa.py_buffer(ends.tobytes()), flat.buffers()[2]]))
        return out

    def _slice(self, texts: list[str]) -> Iterator[list[bytes]]:
        low: list[str] = []
        odd: dict[int, str] = {}
        for k, t in enumerate(texts):
            plain = "<|" not in t and _PLAIN.fullmatch(t)
            if plain and not t.isascii():
                t = unicodedata.normalize("NFC", t)
            even = t.lower() if plain else ""
            if not plain or not (even.isascii() or _PLAIN.fullmatch(even)):
                odd[k] = texts[k]
                even = ""
            low.append(even)
        parts = pc.ascii_split_whitespace(pa.array(low, pa.string()))
        numbered = parts.values.dictionary_encode()
        place, columns = self.chunks.of(numbered.dictionary)
        inside = pa.array(place[numbered.indices.to_numpy()])  # chunks are taken in the order of the texts
        bounds = parts.offsets.to_numpy()
        ready = []
        for column in columns:
            whole = column.take(inside)
            ends = np.frombuffer(whole.buffers()[1], np.int32, len(whole) + 1) if len(whole) else np.zeros(1, np.int32)
            ready.append((memoryview(whole.buffers()[2] or b""), ends[bounds].tolist()))
        for k in range(len(texts)):
            if k in odd:
                yield [b"".join(x) for x in self._parted(self.words.of(words_of(self.voc, odd[k])))]
            else:
                yield [bytes(data[at[k] : at[k + 1]]) for data, at in ready]

    def encode(self, texts: list[str]) -> Iterator[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        for i, j in slices(texts, TEXT_SLICE):
            yield from (x[0] for x in self._slice(texts[i:j]))

    def encode_and_decode(self, texts: list[str]) -> Iterator[tuple[bytes, bytes]]:
        for i, j in slices(texts, TEXT_SLICE):
            yield from ((ids, shown[1:]) for ids, shown in self._slice(texts[i:j]))


def encoder(path: str, lexicon: str | None = None, decoded: bool = False) -> Encoder:
    """This process's encoder: what it remembers serves the tasks that follow."""
    return remembered(("bpe", path, lexicon, decoded), lambda: Encoder(vocabulary(path), mapped(lexicon) if lexicon else None, decoded))


def decode(voc: Vocabulary, ids: np.ndarray) -> str:
    """The text of ids: token strings with blanks between."""
    return " ".join([voc.tokens[i] for i in ids.tolist()])


def word_counts(docs: DataFrame, path: str, text_col: str = "text") -> DataFrame:
    """Count of every word over whole texts: summed in each task first, then across tasks."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("bpe")
        voc = vocabulary(path)
        seen: Counter = Counter()

        def flush() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"])
            seen.clear()
            return out

        for batch in batches:
            for _, _, texts in text_slices(batch.column(0)):
                for text in texts:
                    seen.update(words_of(voc, text or ""))
                if len(seen) > COUNT_WORDS:
                    yield flush()
        yield flush()
        give_back()

    return docs.select(text_col).mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def build_lexicon(docs: DataFrame, path: str, size: int = LEXICON_WORDS, text_col: str = "text") -> str:
    """Compiles the `size` most frequent words of all texts and ships the file; returns its name on executors.

    At most `size` words of at most LEXICON_WORD_BYTES bytes come to the driver, whatever the corpus holds.
    """
    voc = vocabulary(path)
    short = F.octet_length("word") <= LEXICON_WORD_BYTES
    frequent = word_counts(docs, path, text_col).where(short).orderBy(F.desc("n"), "word").limit(size)
    words = [r[0] for r in frequent.select("word").toLocalIterator() if r[0] not in voc.special]
    name = f"lexicon-{uuid.uuid4().hex}.bin"
    folder = tempfile.mkdtemp(prefix="ctxrelease-")  # only on the driver; Spark serves it to the executors as long as it runs
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    compile_lexicon([w.encode() for w in words], voc.merge, os.path.join(folder, name))
    docs.sparkSession.sparkContext.addFile(os.path.join(folder, name))
    return name


def encode_documents(docs: DataFrame, path: str | None = None, size: int = LEXICON_WORDS, text_col: str = "text", key: str = "doc_id") -> DataFrame:
    """Per row: its key, n_tokens, ids_sha256 and decoded_sha256. Rows may repeat; null texts count as empty."""
    path = path or default_path()
    name = build_lexicon(docs, path, size, text_col)
    fields = [T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]

    def maker():
        coder = encoder(path, name, True)

        def work(texts: list[str | None]) -> list[list]:
            out: list[list] = [[], [], []]
            for ids, shown in coder.encode_and_decode([t or "" for t in texts]):
                out[0].append(len(ids) // 4)
                out[1].append(hashlib.sha256(ids).hexdigest())
                out[2].append(hashlib.sha256(shown).hexdigest())
            return out

        return work

    return append_columns(docs, text_col, fields, maker, [key], "bpe")


def op10_bpe(spark, sf_dir: str) -> DataFrame:
    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
