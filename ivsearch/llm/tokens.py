"""Token ids of whole texts by a public vocabulary file, with a bounded cache of pieces."""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: A part that begins a token by itself and ends before the next part.
PART = re.compile(r"\n?\S{1,64}").fullmatch
#: Between letters and these a token always ends.
POINTS = ".,;:!?"
#: Bytes of text handled at a time, words of letters in one string for the library.
GROUP, RUN = 4_000_000, 200


def _alphabet() -> np.ndarray:
    """The character that stands for each byte in a byte-level vocabulary; a space, which none has there, for byte 0."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = iter(range(0x100, 0x200))
    return np.array([0x20, *[b if b in own else next(other) for b in range(256)][1:]], "<u4")


def _runs(start: np.ndarray, n: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each run of n, one run after another."""
    end = np.cumsum(n, dtype=np.int64)
    out = np.repeat((start - (end - n)).astype(np.int32), n)
    out += np.arange(len(out), dtype=np.int32)
    return out


def _bytes(words: pa.Array) -> np.ndarray:
    """UTF-8 bytes of all words, one after another; none is null."""
    at = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1]
    return np.frombuffer(words.buffers()[2] or b"", np.uint8)[at[0] : at[-1]]


class Parts:
    """Ids of parts, at the places that these have in an array."""

    def __init__(self):
        self.words = pa.nulls(1, pa.string())  # place 0 is nobody's
        self.start, self.n, self.data = np.zeros(1, np.int32), np.zeros(1, np.int32), np.zeros(0, "<u4")

    def __len__(self) -> int:
        return len(self.words) - 1

    def find(self, parts: pa.Array, since: int = 0) -> np.ndarray:
        """Their places; -1 for parts that are not here. since: a number of parts that need not be looked at."""
        at = pc.index_in(parts, value_set=self.words.slice(since + 1)).fill_null(-1).to_numpy().astype(np.int64)
        return np.where(at < 0, -1, at + since + 1)

    def ids(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the parts at these places, one after another, and how many each has."""
        n = self.n.take(places)
        return self.data.take(_runs(self.start.take(places), n)), n

    def add(self, parts: pa.Array, ids: np.ndarray, n: np.ndarray) -> None:
        """Distinct parts that are not here yet."""
        self.words = pa.concat_arrays([self.words, parts])
        self.start = np.concatenate([self.start, (len(self.data) + np.cumsum(n) - n).astype(np.int32)])
        self.n, self.data = np.concatenate([self.n, n.astype(np.int32)]), np.concatenate([self.data, ids])


class Encoder:
    """Ids of texts, as little-endian unsigned 32-bit integers, equal to those of Tokenizer.encode(add_special_tokens=False).

    The byte-level pre-tokenizer never lets a token cross a single space, or a single newline's front, between two characters
    that are not white space. So a text is parted there (a part after a newline begins with it), and the parts, which recur,
    are kept in a cache; where other white space stands, the parts around it stay together and are encoded as they are. The
    cache has two generations of about max_parts parts, and tasks drop it when they end: when the younger
    is full it replaces the older, and a part that is met again moves into the younger. Arrow parts a group of texts, numbers their distinct
    parts and finds them in the cache, whose parts are an Arrow array too: hardly any part becomes a Python object, so a cache takes
    some 30 bytes a part. Ids of all parts are gathered by these numbers. New parts of a group are encoded together:
    a token that begins with a space or newline begins a part. Words of letters, which the pre-tokenizer keeps whole, go to the
    library's model spelt in the byte-level alphabet, and punctuation after them apart.
    """

    def __init__(self, path: str, max_parts: int = 500_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
        self.plain = Tokenizer(self.tokenizer.model)  # one model for both
        self.plain.pre_tokenizer = pre_tokenizers.CharDelimiterSplit(" ")
        self.max_parts = max_parts
        self.known, self.older, self.points = Parts(), Parts(), Parts()
        self.alphabet = _alphabet()
        words = self.tokenizer.get_vocab(with_added_tokens=True)
        self.opens = np.zeros(max(words.values()) + 1, bool)
        self.opens[[i for w, i in words.items() if w[:1] in ("\u0120", "\u010a")]] = True  # a space and a newline in the byte-level alphabet

    def _encode(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def forget(self) -> None:
        """Drops the cache, and memory that Arrow holds unused: the worker may next serve a task of another kind, or wait."""
        self.known, self.older = Parts(), Parts()
        pa.default_memory_pool().release_unused()

    def ids(self, text: str | None) -> bytes:
        return self.many([text])[0]

    def rows(self, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int | None, bytes]]:
        """doc_id and ids of each row; batches are gathered until they hold about GROUP bytes of text."""
        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.column("text").nbytes
            if size >= GROUP:
                yield from self._rows(held)
                held, size = [], 0
        yield from self._rows(held)

    def _rows(self, held: list[pa.RecordBatch]) -> Iterator[tuple[int | None, bytes]]:
        if held:
            docs, texts = (pa.concat_arrays([b.column(c) for b in held]) for c in ("doc_id", "text"))
            yield from zip(docs.to_pylist(), self.many(texts, 2 * GROUP))

    def many(self, texts: list[str | None] | pa.Array, size: int = GROUP) -> list[bytes]:
        """Ids of each text; texts are taken in groups of about so many bytes, whose new parts are encoded together."""
        texts = pc.fill_null(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()), "")
        part = np.cumsum(pc.binary_length(texts).to_numpy(), dtype=np.int64) // size
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(part)]
        return [x for i, j in zip(cuts, cuts[1:]) if j > i for x in self._group(texts.slice(i, j - i))]

    def _group(self, texts: pa.Array) -> list[bytes]:
        if len(self.known) > self.max_parts:
            self.known, self.older = Parts(), self.known
        parts = pc.split_pattern(pc.replace_substring(texts, "\n", " \n"), " ")
        at = parts.offsets.to_numpy().astype(np.int64)
        first, coded = at[:-1], parts.flatten().dictionary_encode()  # every text has a first part, be it empty
        index, words = coded.indices.to_numpy(), coded.dictionary
        start, n, data, lost = self._table(words)
        heads, which = np.unique(index[first], return_inverse=True)
        heads = words.take(pa.array(heads)).to_pylist()
        codes, which = self._encode(heads), which.tolist()
        bare = np.array([head != "" and not head[0].isspace() and not head[-1].isspace() for head in heads])
        unknown, each = lost.take(index), n.take(index)
        each[first], unknown[first] = 0, False  # no space or newline precedes a first word
        raw = data.take(_runs(start.take(index), each)).tobytes()
        bounds = [0, *(4 * np.cumsum(each, dtype=np.int64)[at[1:] - 1]).tolist()]
        apart = np.logical_or.reduceat(unknown, first) | ~bare.take(which)
        out = [b"" if a else codes[w] + raw[i:j] for a, w, i, j in zip(apart.tolist(), which, bounds, bounds[1:])]
        if some := np.flatnonzero(apart).tolist():
            own = [index[at[i] : at[i + 1]] for i in some]
            used = np.unique(np.concatenate(own))
            used = used[~lost.take(used)]
            have = {t: data[i : i + k].tobytes() for t, i, k in zip(words.take(pa.array(used)).to_pylist(), start.take(used).tolist(), n.take(used).tolist())}
            for i, x in zip(some, self._apart([words.take(pa.array(o)).to_pylist() for o in own], have)):
                out[i] = x
        return out

    def _table(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Where the ids of each of these distinct parts start in an array, how many it has, that array, and which parts have none: long ones and those with other white space than a newline before them.

        The cache holds words of letters without the punctuation after them, and what is no such word as it is.
        """
        bare = pc.utf8_rtrim(words, POINTS)
        tail = pc.binary_length(words).to_numpy() - pc.binary_length(bare).to_numpy()
        word = self._is_word(bare) & (tail <= 4)
        keys = pc.if_else(pa.array(word), bare, words).dictionary_encode()
        place = self.known.find(keys.dictionary)
        if len(new := np.flatnonzero(place < 0)):
            fresh, had = keys.dictionary.take(pa.array(new)), len(self.known)
            self._learn(fresh)
            place[new] = self.known.find(fresh, had)
        place = place.take(keys.indices.to_numpy())
        known, points, lost = self.known, self.points, place < 0
        place[lost] = 0
        start, n, data = known.start.take(place), known.n.take(place), known.data
        if len(closed := np.flatnonzero(word & (tail > 0) & ~lost)):
            # The last bytes of each as a number; there are at most 6 + 6^2 + 6^3 + 6^4 of them.
            end, tail, chars = np.cumsum(pc.binary_length(words).to_numpy())[closed], tail[closed], _bytes(words)
            last = sum(np.where(k < tail, chars.take(np.maximum(end - 1 - k, 0)), 0).astype(np.int64) << 8 * k for k in range(4))
            ends, which = np.unique(last, return_inverse=True)
            ends = pa.array([e.to_bytes(4, "big").lstrip(b"\0").decode() for e in ends.tolist()])
            if len(fresh := ends.filter(pa.array(points.find(ends) < 0))):
                codes = [np.frombuffer(c, "<u4") for c in self._encode(fresh.to_pylist())]
                points.add(fresh, np.concatenate(codes), np.array([len(c) for c in codes]))
            # Of each a stem from the one table, then an ending from the other.
            end = points.find(ends).take(which)
            both = np.stack([n[closed], points.n.take(end)], 1)
            two = np.concatenate([data, points.data]).take(_runs(np.stack([start[closed], points.start.take(end) + len(data)], 1).ravel(), both.ravel()))
            n[closed] = both.sum(1)
            start[closed], data = len(data) + np.cumsum(n[closed]) - n[closed], np.concatenate([data, two])
        return start, n, data, lost

    def _is_word(self, parts: pa.Array) -> np.ndarray:
        return (pc.utf8_length(parts).to_numpy() <= 64) & pc.utf8_is_alpha(pc.utf8_ltrim(parts, "\n")).to_numpy(zero_copy_only=False)

    def _learn(self, parts: pa.Array) -> None:
        """Ids of new parts go to the younger generation, where they can be told."""
        if len(self.older):
            met = self.older.find(parts)
            self.known.add(parts.filter(pa.array(met >= 0)), *self.older.ids(met[met >= 0]))
            parts = parts.filter(pa.array(met < 0))
        word = self._is_word(parts)
        self._spell(parts.filter(pa.array(word)))
        self._mixed([p for p in parts.filter(pa.array(~word)).to_pylist() if PART(p)])

    def _spell(self, words: pa.Array) -> None:
        """Learns words of letters, some with a newline before them, which is a token by itself."""
        if len(words):
            cuts = np.minimum(np.arange(0, len(words) + RUN, RUN), len(words)).astype(np.int32)
            runs = pc.binary_join(pa.ListArray.from_arrays(pa.array(cuts), words), "\0 ")
            runs = pc.replace_substring(pc.binary_join_element_wise("\0 ", runs, ""), "\0 \n", "\0\n\0")
            end = np.cumsum(pc.binary_length(runs).to_numpy(), dtype=np.int64).tolist()
            spelt = self.alphabet[_bytes(runs)].tobytes().decode("utf-32-le")  # a character a byte
            runs = [spelt[i + 1 : j] for i, j in zip([0, *end], end)]
            some = (self.plain.encode_batch_fast(runs[i : i + 64], add_special_tokens=False) for i in range(0, len(runs), 64))
            self._keep(words, [np.array(e.ids, "<u4") for codes in some for e in codes])

    def _mixed(self, parts: list[str]) -> None:
        self._keep(pa.array(parts, pa.string()), [np.frombuffer(self._encode([" ".join(["x", *parts]).replace(" \n", "\n")])[0], "<u4")[1:]])

    def _keep(self, parts: pa.Array, codes: list[np.ndarray]) -> None:
        if len(parts):
            ids = np.concatenate(codes)
            starts = np.flatnonzero(self.opens[ids])
            if len(starts) == len(parts):
                self.known.add(parts, ids[starts[0] :], np.diff(starts, append=len(ids)))

    def _apart(self, texts: list[list[str]], have: dict[str, bytes]) -> list[bytes]:
        """Ids of texts given as their parts, some of which have theirs; other chunks are encoded once for all texts."""
        heads, tails = [], []
        for head, *tail in texts:
            chunks, closed = [head], head != "" and not head[-1].isspace()
            for part in tail:
                first = part[1:2] if part[:1] == "\n" else part[:1]
                if closed and first and not first.isspace():
                    chunks.append(part)
                else:
                    chunks[-1] += " " + part
                closed = part != "" and not part[-1].isspace()
            heads.append(chunks[0].replace(" \n", "\n"))
            tails.append(chunks[1:])
        new = [t for t in dict.fromkeys(t for tail in tails for t in tail) if t not in have]
        codes = self._encode([*heads, *((" " + t).replace(" \n", "\n") for t in new)])
        have |= zip(new, codes[len(heads) :])
        return [b"".join([start, *(have[t] for t in tail)]) for start, tail in zip(codes, tails)]


_SHARED: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One for each Python worker, which Spark uses for many tasks."""
    if path not in _SHARED:
        _SHARED[path] = Encoder(path)
    return _SHARED[path]


def vocabulary() -> str:
    """The default vocabulary; any other file can be passed by its path."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")
