"""Byte-pair encoding from a tokenizer file: vectorised for many short words, streamed for long runs.

``MergeTable`` applies a merge list to a batch of short symbol rows at once (numpy), and to a
long run of any length in windows, with the right context that the merge list can need at most
(``MergeTable.lookahead``).  ``TextStream`` is the transducer of one text: it takes blocks, and emits
tokens once they are stable.  ``ByteStreamEncoder`` advances many streams in step, so that the words
all of them wait for are merged together and remembered.  ``ByteStreamDecoder`` turns ids back into
text with an incremental UTF-8 state machine.  ``WordEncoder`` holds the lower-casing word vocabulary.
Caches are bounded, so a task's memory does not grow with its input.
"""

from __future__ import annotations

import codecs
import heapq
import json
import re
import sys
import unicodedata
from bisect import bisect_left
from functools import lru_cache

import numpy as np
import regex

#: Most words or chunks that a cache holds; it starts anew beyond.
CACHE = 600_000
#: Rows up to this many symbols are merged in a matrix, longer ones by a heap and windows.
SHORT = 48
END = "<|endoftext|>"
# Marks that are words of their own behind letters.
MARKS = frozenset(".,;:!?")


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters, extra = {b: chr(b) for b in plain}, 256
    for b in range(256):
        if b not in letters:
            letters[b] = chr(extra)
            extra += 1
    return [letters[b] for b in range(256)]


class MergeTable:
    def __init__(self, merges: list[tuple[int, int, int]], width: np.ndarray):
        """merges: (left, right, result) ids in order of rank; width: bytes of each id."""
        self.width = width
        self.pairs = {(a, b): (r, c) for r, (a, b, c) in enumerate(merges)}
        left, right, result = (np.array(x, np.int64) for x in zip(*merges, strict=True))
        key = left << 32 | right
        order = np.argsort(key)
        self.keys, self.rank, self.made = key[order], np.arange(len(key))[order], result[order]
        self.none = len(key)
        self.lookahead = self._lookahead(merges)

    def _lookahead(self, merges) -> int:
        """Bytes right of a boundary that can decide it.

        Whether merge (u, v) applies depends on merges of lower rank that could take v, or a
        right part of v before v is whole, together with some t to its right; these again
        depend on what lies right of t.  Ranks fall along such a chain, so one pass in order
        of rank finds the longest: per left operand the ranks and the running maximum.
        """
        parts, by_left, most = {}, {}, 1
        for rank, (a, b, c) in enumerate(merges):
            beyond, s, limit = 0, b, rank
            while True:
                ranks, reach = by_left.get(s, ((), ()))
                if k := bisect_left(ranks, limit):
                    beyond = max(beyond, reach[k - 1])
                if s not in parts:
                    break
                limit, s = parts[s]
            parts.setdefault(c, (rank, b))
            ranks, reach = by_left.setdefault(a, ([], []))
            ranks.append(rank)
            reach.append(max(int(self.width[b]) + beyond, reach[-1] if reach else 0))
            most = max(most, reach[-1])
        return most

    def _find(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = a << 32 | b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[at] == key
        return np.where(hit, self.rank[at], self.none), self.made[at]

    def encode_words(self, words: list[bytes], inner: np.ndarray, last: np.ndarray) -> list[bytes]:
        """Little-endian ids of every non-empty word; inner and last map bytes to symbols."""
        out = [b""] * len(words)
        size = np.fromiter(map(len, words), np.int64, len(words))
        for n in np.unique(size):
            where = np.flatnonzero(size == n)
            if n > SHORT:
                for i in where:
                    row = np.frombuffer(words[i], np.uint8)
                    out[i] = self.encode_long([*inner[row[:-1]].tolist(), int(last[row[-1]])]).tobytes()
            elif n:
                rows = np.frombuffer(b"".join([words[i] for i in where.tolist()]), np.uint8).reshape(-1, n)
                self._matrix(np.concatenate([inner[rows[:, :-1]], last[rows[:, -1:]]], axis=1), where, out)
        return out

    def _matrix(self, sym: np.ndarray, where: np.ndarray, out: list[bytes]) -> None:
        """Rows of one length; each step merges the best leftmost pair of every open row."""
        n = sym.shape[1]
        rank, made = self._find(sym[:, :-1], sym[:, 1:])
        while len(sym):
            row = np.arange(len(sym))
            if n > 1:
                best = rank.argmin(1)
                open_ = rank[row, best] < self.none
            else:
                open_ = np.zeros(len(sym), bool)
            shut = ~open_
            if shut.any():
                flat = sym[shut].astype("<u4").tobytes()
                for k, i in enumerate(where[shut].tolist()):
                    out[i] = flat[4 * n * k : 4 * n * (k + 1)]
                sym, where = sym[open_], where[open_]
                if not len(sym):
                    return
                rank, made, best = rank[open_], made[open_], best[open_]
                row = np.arange(len(sym))
            sym[row, best] = made[row, best]
            keep = np.ones(sym.shape, bool)
            keep[row, best + 1] = False
            sym = sym[keep].reshape(len(sym), n - 1)
            keep = np.ones(rank.shape, bool)
            keep[row, np.minimum(best + 1, n - 2)] = False
            rank, made = rank[keep].reshape(len(sym), n - 2), made[keep].reshape(len(sym), n - 2)
            n -= 1
            for at in (best - 1, best):
                ok = np.flatnonzero((at >= 0) & (at < n - 1))
                if len(ok):
                    rank[ok, at[ok]], made[ok, at[ok]] = self._find(sym[ok, at[ok]], sym[ok, at[ok] + 1])

    def encode_heap(self, row: list[int]) -> list[int]:
        """One row by a heap of pairs: n log n."""
        sym, n = list(row), len(row)
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(*self.pairs[p], i) for i, p in enumerate(zip(row, row[1:], strict=False)) if p in self.pairs]
        heapq.heapify(heap)
        while heap:
            rank, new, i = heapq.heappop(heap)
            j = nxt[i]
            if sym[i] < 0 or j >= n or self.pairs.get((sym[i], sym[j])) != (rank, new):
                continue
            sym[i], sym[j], nxt[i] = new, -1, nxt[j]
            if nxt[j] < n:
                prv[nxt[j]] = i
                if (p := (new, sym[nxt[i]])) in self.pairs:
                    heapq.heappush(heap, (*self.pairs[p], i))
            if prv[i] >= 0 and (p := (sym[prv[i]], new)) in self.pairs:
                heapq.heappush(heap, (*self.pairs[p], prv[i]))
        return [x for x in sym if x >= 0]

    def encode_long(self, row: list[int]) -> np.ndarray:
        run = LongRun(self)
        out = [run.feed(row[i : i + 4096]) for i in range(0, len(row), 4096)]
        return np.array([*(x for part in out for x in part), *run.finish()], "<u4")


class LongRun:
    """Tokens of one unbounded run of symbols, each emitted once no later symbol can change it."""

    def __init__(self, table: MergeTable):
        self.table, self.held = table, []

    def feed(self, symbols: list[int]) -> list[int]:
        self.held += symbols
        if len(self.held) <= 2 * self.table.lookahead:
            return []
        ids, done, at = self.table.encode_heap(self.held), 0, 0
        for k, x in enumerate(ids):
            if at + int(self.table.width[x]) > len(self.held) - self.table.lookahead:
                break
            at, done = at + int(self.table.width[x]), k + 1
        self.held = self.held[at:]
        return ids[:done]

    def finish(self) -> list[int]:
        ids, self.held = self.table.encode_heap(self.held), []
        return ids


class ByteVocabulary:
    """A byte-level BPE file: every id is a run of bytes."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, back = spec["model"], {c: b for b, c in enumerate(byte_letters())}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*model["vocab"].values(), *self.special.values()]) + 1
        text: list[bytes] = [b""] * size
        for token, i in model["vocab"].items():
            text[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in self.special.items():
            text[i] = token.encode()
        self.text = text
        self.width = np.array([len(x) for x in text], np.int64)
        self.first = np.zeros(size + 1, np.int64)
        np.cumsum(self.width, out=self.first[1:])
        self.flat = np.frombuffer(b"".join(text), np.uint8)
        vocab = model["vocab"]
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.symbol = np.array([vocab[c] for c in byte_letters()], np.int64)
        self.merges = MergeTable([(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs], self.width)


@lru_cache(maxsize=4)
def byte_vocabulary(path: str) -> ByteVocabulary:
    return ByteVocabulary(path)


# The word pattern that the byte-level vocabulary was made with.
BYTE_WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
# The runs of one class that a word of that pattern can end in.
RUNS = [regex.compile(r"\p{L}+"), regex.compile(r"\p{N}+"), regex.compile(r"[^\s\p{L}\p{N}]+"), regex.compile(r"\s+")]


class Chunks:
    """Bounded caches: the ids of words, and of chunks of words the ids or their number."""

    def __init__(self):
        self.chunks: dict[str, bytes] = {}
        self.sizes: dict[str, int] = {}
        self.words: dict[str, bytes] = {}

    def _fill(self, keys, forms, pattern, merges: MergeTable, inner, last, sizes: bool) -> None:
        """Ids of the chunks ``keys``, whose words the pattern finds in ``forms``, or only their number.

        A run of letters, behind a space or not, is one word, and so is a mark at its end.
        """
        words, one, two, more = self.words, [], [], []
        for c, f in zip(keys, forms, strict=True):
            body = f[1:] if f[:1] == " " else f
            if body.isalpha():
                one.append((c, f))
            elif body[-1:] in MARKS and body[:-1].isalpha():
                two.append((c, f[:-1], f[-1]))
            else:
                more.append((c, pattern.findall(f)))
        new = {f for _, f in one}
        new.update(f for _, f, _ in two)
        new.update(m for _, _, m in two)
        new.update(w for _, ws in more for w in ws)
        new = [w for w in new if w not in words]
        words.update(zip(new, merges.encode_words([w.encode() for w in new], inner, last), strict=True))
        if sizes:
            n = self.sizes
            for c, f in one:
                n[c] = len(words[f]) >> 2
            for c, f, m in two:
                n[c] = len(words[f]) + len(words[m]) >> 2
            for c, ws in more:
                n[c] = sum(len(words[w]) for w in ws) >> 2
            return
        chunks = self.chunks
        for c, f in one:
            chunks[c] = words[f]
        for c, f, m in two:
            chunks[c] = words[f] + words[m]
        for c, ws in more:
            chunks[c] = b"".join([words[w] for w in ws])

    def _missing(self, split, cache: dict) -> set[str]:
        """Chunks that the cache lacks; a cache that would outgrow its limit starts anew."""
        wanted = set().union(*split)
        missing = wanted - cache.keys()
        if len(cache) + len(missing) > CACHE:
            cache.clear()
            missing = wanted
        if len(self.words) > CACHE:
            self.words.clear()
        return missing


class ByteStreamEncoder(Chunks):
    """Encodes texts; ids come as little-endian bytes."""

    #: Longest chunk that is merged whole; a longer one is a run of its stream.
    LIMIT = 4096
    #: Characters that a stream takes at a time.
    STEP = 1 << 16

    def __init__(self, path: str):
        super().__init__()
        self.v = byte_vocabulary(path)

    def learn(self, split, sizes: bool = False) -> None:
        """Merges, all together, the chunks of these texts that are not remembered."""
        missing = [c for c in self._missing(split, self.sizes if sizes else self.chunks) if len(c) <= self.LIMIT]
        self._fill(missing, missing, BYTE_WORDS, self.v.merges, self.v.symbol, self.v.symbol, sizes)

    @staticmethod
    def split(text: str) -> list[str]:
        """Cuts before each space that a word follows; such a place always ends a word."""
        first, *rest = text.split(" ")
        if "  " not in text and not text.endswith(" ") and " \n" not in text and "\t" not in text and "\r" not in text and text.isascii():
            return [first, *(" " + x for x in rest)] if first else [" " + x for x in rest]
        out = [first]
        for x in rest:
            if x and not x[0].isspace():
                out.append(" " + x)
            else:
                out[-1] += " " + x
        return out if out[0] else out[1:]

    def steps(self, text: str):
        """(block, what ends the text's part behind it): None, no ids, or the id of a special string."""
        at = 0
        while True:
            end = text.find(END, at) if END in self.v.special else -1
            stop = len(text) if end < 0 else end
            while stop - at > self.STEP:
                yield text[at : at + self.STEP], None
                at += self.STEP
            yield text[at:stop], b"" if end < 0 else self.v.special[END].to_bytes(4, "little")
            if end < 0:
                return
            at = end + len(END)

    def advance(self, work: list[tuple["TextStream", str, bytes | None]]) -> list[bytes]:
        """Gives every stream its next block; returns the ids that are stable then."""
        ready = [stream.take(block, end is not None) for stream, block, end in work]
        self.learn([x for _, x in ready])
        get, out = self.chunks.__getitem__, []
        for (stream, _, end), (held, split) in zip(work, ready, strict=True):
            try:
                got = held + b"".join(map(get, split))
            except KeyError:  # an overlong chunk
                got = held + b"".join(map(self.whole, split))
            if end is not None:
                got += stream.finish() + end
            out.append(got)
        return out

    def whole(self, chunk: str) -> bytes:
        """Ids of a chunk of any length."""
        if len(chunk) <= self.LIMIT:
            if chunk not in self.chunks:
                self.learn([[chunk]])
            return self.chunks[chunk]
        own = TextStream(self)
        parts = [own.feed(chunk[i : i + self.LIMIT]) for i in range(0, len(chunk), self.LIMIT)]
        return b"".join([*parts, own.finish()])

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of whole texts, each through its own stream."""
        out: list[list[bytes]] = [[] for _ in texts]
        for k, got in self.rounds(texts):
            out[k].append(got)
        return [b"".join(x) for x in out]

    def rounds(self, texts: list[str]):
        """(number of the text, ids that became stable), block by block, all texts in step."""
        open_ = [(k, TextStream(self), self.steps(t)) for k, t in enumerate(texts)]
        while open_:
            todo = [(x, step) for x in open_ if (step := next(x[2], None)) is not None]
            open_ = [x for x, _ in todo]
            yield from zip([k for k, _, _ in open_], self.advance([(x[1], *step) for x, step in todo]), strict=True)

    def lengths(self, texts: list[str]) -> list[int]:
        """Numbers of tokens of whole texts; ids are not kept."""
        split = [None if len(t) > self.STEP or END in t else self.split(t) for t in texts]
        self.learn([s for s in split if s is not None], sizes=True)
        get, out = self.sizes.__getitem__, []
        for t, s in zip(texts, split, strict=True):
            try:
                out.append(sum(map(get, s)) if s is not None else len(self.encode([t])[0]) >> 2)
            except KeyError:  # an overlong chunk
                out.append(len(self.encode([t])[0]) >> 2)
        return out


class TextStream:
    """The transducer of one text: open end, and the open run of an overlong word.

    A word boundary of the pattern is stable once the characters behind it are known, so all
    but the open end of the buffer is encoded at once.  An open word beyond ``LIMIT`` becomes a
    run: its bytes go to ``LongRun``, which emits tokens as the lookahead permits.
    """

    def __init__(self, encoder: ByteStreamEncoder):
        self.encoder, self.v = encoder, encoder.v
        self.tail, self.run, self.long = "", None, None

    def take(self, block: str, last: bool) -> tuple[bytes, list[str]]:
        """Ids that are stable already, and stable chunks for the encoder to look up."""
        if self.run is not None:
            return self.feed(block), []
        s = self.tail + block
        at = len(s) if last else next((i for i in range(len(s) - 2, 0, -1) if s[i] == " " and not s[i + 1].isspace()), 0)
        self.tail = s[at:]
        if len(self.tail) > self.encoder.LIMIT:
            self.tail = ""
            return self.feed(s), []
        return b"", self.encoder.split(s[:at]) if at else []

    def _push(self, text: str) -> bytes:
        return np.array(self.long.feed(self.v.symbol[np.frombuffer(text.encode(), np.uint8)].tolist()), "<u4").tobytes()

    def _close(self) -> bytes:
        self.run = None
        return np.array(self.long.finish(), "<u4").tobytes()

    def _whole(self, text: str) -> bytes:
        """Ids of text that ends at a stable boundary."""
        return b"".join(map(self.encoder.whole, self.encoder.split(text))) if text else b""

    def feed(self, block: str) -> bytes:
        out, s = [], self.tail + block
        self.tail = ""
        if self.run is not None and s:
            end = m.end() if (m := self.run.match(s)) else 0
            space = self.run is RUNS[3]
            out.append(self._push(s[: end - 1] if space and end else s[:end]))
            s = s[max(0, end - 1) if space else end :]
            if end and (not s or space and len(s) == 1):
                self.tail = s
                return b"".join(out)
            out.append(self._close())
        at = next((i for i in range(len(s) - 2, 0, -1) if s[i] == " " and not s[i + 1].isspace()), 0)
        out.append(self._whole(s[:at]))
        s = s[at:]
        if len(s) > self.encoder.LIMIT:
            ws = BYTE_WORDS.findall(s)
            last = ws[-1]
            if len(last) > self.encoder.LIMIT // 2:
                out.append(self._words(ws[:-1]))
                self.run, self.long = next(r for r in RUNS if r.match(last[-1])), LongRun(self.v.merges)
                space = self.run is RUNS[3]
                out.append(self._push(last[:-1] if space else last))
                s = last[-1] if space else ""
            else:
                out.append(self._words(ws[:-4]))
                s = "".join(ws[-4:])
        self.tail = s
        return b"".join(out)

    def _words(self, words: list[str]) -> bytes:
        """Ids of words of the pattern, the long ones by windows."""
        symbol = self.v.symbol
        return b"".join([self.v.merges.encode_long(symbol[np.frombuffer(w.encode(), np.uint8)].tolist()).tobytes() for w in words])

    def finish(self) -> bytes:
        s, self.tail = self.tail, ""
        if self.run is not None:
            return self._push(s) + self._close()
        return self._words(BYTE_WORDS.findall(s)) if len(s) > self.encoder.LIMIT else self._whole(s)


class ByteStreamDecoder:
    """Ids to text, block by block; bytes of an unfinished character wait for the next block."""

    def __init__(self, path: str):
        self.v = byte_vocabulary(path)
        self.machine = self.fresh()

    @staticmethod
    def fresh() -> codecs.IncrementalDecoder:
        """The state machine of one text."""
        return codecs.getincrementaldecoder("utf-8")("replace")

    def raw(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.v.text.__getitem__, ids.tolist()))

    def feed(self, ids: np.ndarray) -> str:
        return self.machine.decode(self.raw(ids))

    def finish(self) -> str:
        return self.machine.decode(b"", True)

    def decode(self, ids: np.ndarray, block: int = 1 << 16) -> str:
        out = [self.feed(ids[i : i + block]) for i in range(0, len(ids), block)]
        text = "".join([*out, self.finish()])
        self.machine.reset()
        return text


# The word pattern of the lower-casing vocabulary.
LOWER_WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")
# What the library treats otherwise than splitting at white space does.
ODD = ("<|", "\x1c", "\x1d", "\x1e", "\x1f")


# Full stops and commas behind an ASCII letter or digit and before a space or line end.
SET_OFF = re.compile(r"(?<=[A-Za-z0-9])([.,])(?=[ \n])")


def loose(text: str) -> list[str]:
    """Chunks between white space, with full stops and commas set off from ASCII letters and digits.

    White space makes no token and words end at marks anyway, so setting a mark off changes no
    token unless it stands in a run of marks; it leaves far fewer different chunks.  Behind other
    letters it might: their normal form can end in a combining mark, which is no letter.
    """
    if text.isascii():
        text = text.lower()
    return SET_OFF.sub(r" \1", text).split()


@lru_cache(maxsize=1)
def unassigned() -> re.Pattern:
    """Code points that this Python's Unicode tables lack; the library's may know them."""
    gone = [c for c in range(0x80, sys.maxunicode + 1) if unicodedata.category(chr(c)) == "Cn"]
    first = [c for k, c in enumerate(gone) if not k or gone[k - 1] != c - 1]
    last = [c for k, c in enumerate(gone) if k + 1 == len(gone) or gone[k + 1] != c + 1]
    return re.compile("[" + "".join(f"{chr(a)}-{chr(b)}" for a, b in zip(first, last, strict=True)) + "]")


class WordEncoder(Chunks):
    """Ids of the lower-casing vocabulary with word ends, equal to the library's.

    White space is dropped and never joined, so each chunk between white space is encoded by
    itself and remembered.  Texts with special strings or with the separators that Python, but
    not the library, takes as white space go to the library, and so do chunks with characters
    that Python's Unicode tables lack.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        self.library = Tokenizer.from_file(path)
        self.normal = self.library.normalizer
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab, mark = model["vocab"], model["end_of_word_suffix"]
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        width = np.ones(max(vocab.values()) + 1, np.int64)
        for token, i in vocab.items():
            width[i] = len(token.removesuffix(mark))
        self.merges = MergeTable([(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs], width)
        self.inner = np.array([vocab[c] for c in byte_letters()], np.int64)
        self.last = np.array([vocab[c + mark] for c in byte_letters()], np.int64)
        self.unknown = unassigned()

    def _library_ids(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _learn(self, split, sizes: bool = False) -> None:
        missing = self._missing(split, self.sizes if sizes else self.chunks)
        plain = [c for c in missing if c.isascii()]
        other = [c for c in missing if not c.isascii()]
        # one look at each different character, not at each chunk
        bad = {x for x in set().union(*other) if self.unknown.search(x)}
        odd = [c for c in other if not bad.isdisjoint(c)] if bad else []
        for c in odd:
            got = self._library_ids(c)
            if sizes:
                self.sizes[c] = len(got) >> 2
            else:
                self.chunks[c] = got
        if odd:
            odd = set(odd)
            other = [c for c in other if c not in odd]
        # chunks hold no white space, and normalising neither adds nor takes any
        normal = self.normal.normalize_str(" ".join(other)).split(" ") if other else []
        if len(normal) != len(other):
            normal = [self.normal.normalize_str(c) for c in other]
        self._fill(plain + other, [c.lower() for c in plain] + normal, LOWER_WORDS, self.merges, self.inner, self.last, sizes)

    def _split(self, texts: list[str]) -> list[list[str] | None]:
        return [None if any(x in t for x in ODD) else loose(t) for t in texts]

    def encode(self, texts: list[str]) -> list[bytes]:
        split = self._split(texts)
        self._learn([s for s in split if s is not None])
        get = self.chunks.__getitem__
        return [b"".join(map(get, s)) if s is not None else self._library_ids(t) for t, s in zip(texts, split, strict=True)]

    def lengths(self, texts: list[str]) -> list[int]:
        """Numbers of tokens of whole texts; ids are not kept."""
        split = self._split(texts)
        self._learn([s for s in split if s is not None], sizes=True)
        get = self.sizes.__getitem__
        return [sum(map(get, s)) if s is not None else len(self._library_ids(t)) >> 2 for t, s in zip(texts, split, strict=True)]


@lru_cache(maxsize=4)
def word_encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


@lru_cache(maxsize=4)
def byte_encoder(path: str) -> ByteStreamEncoder:
    return ByteStreamEncoder(path)


def text_blocks(texts: list[str], limit: int = 4 << 20):
    """Slices of a list of texts of about ``limit`` characters in all."""
    i = 0
    while i < len(texts):
        j, size = i, 0
        while j < len(texts) and (j == i or size + len(texts[j]) <= limit):
            size += len(texts[j])
            j += 1
        yield i, j
        i = j
