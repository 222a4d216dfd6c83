"""Byte-level BPE by a lazily determinised finite-state transducer, and a streaming decoder.

Encoding. A sequence of tokens is the encoding of its bytes exactly if each neighbouring pair is stable, that is, if
merging the pair's bytes alone gives the same two tokens. That makes a nondeterministic transducer over bytes: a state
is (last finished token, node of the token trie), and reaching a token's node may finish it when the pair is stable. As
the encoding of each beginning of a word is one sequence, one token at most is finished at a place. `Transducer`
determinises it on demand: a deterministic state is the set of open hypotheses, and notes the token that is finished
there. A word's tokens are read off the states that it passed, from its end back. Hypotheses carry no output, so words
share states whatever tokens came before the last. Transitions are memoised, and dropped when they exceed a bound.

Of the last token a hypothesis keeps only what can still matter. Stability is decided by undoing merges at the seam:
right parts of the last token meet left parts of the next. Where no token below the node has a part that one of the
first right parts would merge with in time, these are undone beforehand; where that holds for all of them, any token
below the node is stable, and the last token is forgotten. So a state tells nearby bytes only, and new words are mostly
made of known transitions.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import without_gc, worker_cache

NONE = -1
#: Longer words are encoded one by one.
LONG = 64
#: How a pattern ends whose other branches match letters, digits or other marks, each after at most one space.
SPACED = r"| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: A pattern that takes letters after a space whole, and then other marks whole, unless an apostrophe is among them.
LETTERS = "'s|'t|'re|'ve|'m|'ll|'d" + SPACED
MARKS = "".join(map(chr, range(33, 48))).replace("'", "") + ":;<=>?@[\\]^_`{|}~"


#: Characters of texts that are encoded at once.
GROUP = 2_000_000


def gather(flat: np.ndarray, begins: np.ndarray, lengths: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """The pieces flat[begins[c] : begins[c] + lengths[c]] of all codes c, one after another."""
    out = []
    for k in range(0, len(codes), 1 << 17):
        some = codes[k : k + (1 << 17)]
        n = lengths[some]
        ends = np.cumsum(n)
        out.append(flat[np.repeat(begins[some] - ends + n, n) + np.arange(ends[-1])])
    return np.concatenate(out) if out else flat[:0]


def flat_bytes(strings: pa.LargeStringArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(all bytes, where each string begins, its length)."""
    _, offsets, data = strings.buffers()
    ends = np.frombuffer(offsets, dtype=np.int64)[strings.offset : strings.offset + len(strings) + 1] if offsets else np.zeros(1, np.int64)
    return np.frombuffer(data, dtype=np.uint8) if data else np.empty(0, np.uint8), ends[:-1], np.diff(ends)


def load_ranks(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def parse_ranks(data: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in (line.split() for line in data.splitlines() if line)}


class Transducer:
    """Byte words to token ids by merge ranks. Not reachable tokens (whose own bytes encode otherwise) stand for whole words only."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, max_states: int = 120_000, max_words: int = 300_000, max_chunks: int = 100_000):
        """pattern: its matches are encoded one by one. The short cut of encode() holds for SPACED patterns only."""
        import regex

        self.find = regex.compile(pattern).findall
        self.apart = re.compile(r" (?<=\s )(?:\s|\Z)").search if pattern.endswith(SPACED) else None
        self.letters = pattern == LETTERS
        self.ranks = ranks
        self.text = Tokens({i: b for b, i in ranks.items()})
        self.packed = {i: i.to_bytes(4, "little") for i in self.text}
        self.max_states, self.max_words, self.max_chunks = max_states, max_words, max_chunks
        self.goto: dict[int, int] = {}  # node << 8 | byte
        self.token, self.inner, self.up = [NONE], [False], [0]  # by node: its token, whether it goes on, the node before
        self.parts: dict[int, tuple[int, int]] = {}
        for b, i in sorted(ranks.items(), key=lambda x: (len(x[0]), x[1])):
            if len(b) == 1 or self._split(b, i):
                self._insert(b, i)
        self._seams()
        never = [b.decode("utf-8", "replace") for b, i in ranks.items() if len(b) > 1 and i not in self.parts]
        self.unreached = [t[1:] for t in never if t[:1] == " "]
        self.words, self.older_words = {}, {}  # packed ids of matches
        self.chunks, self.older_chunks = {}, {}  # and of what stands between two spaces, with the first of them
        self._reset()

    def _insert(self, b: bytes, i: int) -> None:
        node = 0
        for c in b:
            nxt = self.goto.get(node << 8 | c)
            if nxt is None:
                nxt = self.goto[node << 8 | c] = len(self.token)
                self.inner[node] = True
                self.token.append(NONE)
                self.inner.append(False)
                self.up.append(node)
            node = nxt
        self.token[node] = i

    def _split(self, b: bytes, i: int) -> bool:
        """Whether merging b's bytes ends in token i; notes its last merge."""
        parts = self.merge(b)
        if len(parts) != 1:
            return False
        two = self.merge(b, last=True)
        self.parts[i] = (two[0], two[1])
        return True

    def merge(self, b: bytes, last: bool = False) -> list[int]:
        """Lowest rank first, leftmost first, over the bytes of b. last: stop before the merge that would leave one token."""
        ranks, parts = self.ranks, [b[k : k + 1] for k in range(len(b))]
        while len(parts) > (2 if last else 1):
            best, at = None, -1
            for k in range(len(parts) - 1):
                r = ranks.get(parts[k] + parts[k + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, k
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [ranks[p] for p in parts]

    def _seams(self) -> None:
        """What merges across seams: by left part, its possible right parts; by node and token before it, the latest merge that takes this token in."""
        ranks, parts, goto = self.ranks, self.parts, self.goto
        self.joins: dict[int, list[tuple[int, int]]] = {}  # left part: (right part, rank)
        for b, r in ranks.items():
            for k in range(1, len(b)):
                x, y = ranks.get(b[:k]), ranks.get(b[k:])
                if x is not None and y is not None:
                    self.joins.setdefault(x, []).append((y, r))
        self.near: dict[int, tuple[dict[int, int], dict[int, int]]] = {}
        self.taken: dict[int, int] = {}  # node << 32 | token on the way to it: highest rank that merges it on, of tokens at or below the node
        for i in parts:
            path, node = [0], 0
            for c in self.text[i]:
                node = goto[node << 8 | c]
                path.append(node)
            q = i
            while (two := parts.get(q)) is not None:
                y = two[0]
                for n in path[len(self.text[y]) + 1 :]:
                    key = n << 32 | y
                    if self.taken.get(key, NONE) < q:
                        self.taken[key] = q
                q = y
        self.ordered = all(x < i and y < i for i, (x, y) in parts.items())  # parts are merged before their wholes

    def _joins(self, x: int) -> tuple[dict[int, int], dict[int, int]]:
        """By node: the lowest rank of merges of x with a token at or below it; by token: the rank of its merge with x."""
        found = self.near.get(x)
        if found is None:
            below, with_x = {}, {}
            for y, r in self.joins.get(x, ()):
                with_x[y], node = r, 0
                path = [0]
                for c in self.text[y]:
                    node = self.goto.get(node << 8 | c)
                    if node is None:
                        break
                    path.append(node)
                else:
                    for n in path:
                        if r < below.get(n, r + 1):
                            below[n] = r
            found = self.near[x] = below, with_x
        return found

    def _matters(self, x: int, below: int, node: int) -> bool:
        """Whether x, bare once merges from rank `below` on are undone, may merge with a left part of a token at or below the node."""
        under, with_x = self._joins(x)
        if under.get(node, below) < below:
            return True
        n = self.up[node]
        while n:
            y = self.token[n]
            r = with_x.get(y, below) if y != NONE else below
            if r < below and self.taken.get(node << 32 | y, NONE) >= r:
                return True
            n = self.up[n]
        return False

    def _open(self, last: int, node: int) -> tuple[int, int]:
        """The hypothesis (last, node), last being a token, NONE for any, or -2 - p for p with its own merge undone."""
        if last == NONE or not self.ordered:
            return last, node
        while True:
            x, below = (last, len(self.ranks) + 1) if last >= 0 else (self.parts[-2 - last][1], -2 - last)
            if self._matters(x, below, node):
                return last, node
            if x not in self.parts:
                return NONE, node
            last = -2 - x

    def _apart(self, a: int, b: int) -> bool:
        """Whether a and b stay apart: undo their merges, latest first, and see if an earlier one would cross the seam."""
        ranks, text, parts = self.ranks, self.text, self.parts
        below = len(ranks) + 1  # a merge across the seam wins only if its rank is under this
        if a < NONE:  # a's merge is undone already, and so are later ones of b
            below = -2 - a
            while b >= below and b in parts:
                b = parts[b][0]
            a = parts[below][1]
        while True:
            joined = ranks.get(text[a] + text[b])
            if joined is not None and joined < below:
                return False
            left, right = parts.get(a), parts.get(b)
            if left is None and right is None:
                return True
            if right is None or (left is not None and a > b):
                below, a = a, left[1]  # of equal ranks the leftmost merge goes first, so b's own merge wins ties
            else:
                below, b = b + 1, right[0]

    def _reset(self) -> None:
        start = ((NONE, 0),)  # hypotheses: last token, node
        self.ids, self.sets, self.ends = {(start, NONE): 0}, [start], [NONE]
        self._room(min(self.max_states, 1024))
        self.moves: dict[tuple[int, int], dict[int, tuple]] = {}  # by hypothesis: byte to (hypothesis, token finished)
        self.fresh: dict[int, tuple[int, int]] = {}
        self.moved = 0

    def _room(self, states: int) -> None:
        """Tables for so many states: next state by state << 8 | byte, 0 where unknown, as nothing leads to the first; token finished."""
        table, over = np.zeros(states << 8, dtype=np.int32), np.full(states, NONE, dtype=np.int64)
        if len(self.sets) > 1:
            table[: len(self.table)], over[: len(self.over)] = self.table, self.over
        self.table, self.over, self.at = table, over, memoryview(table)

    def _move(self, h: tuple[int, int], c: int) -> tuple:
        last, node = h
        nxt = self.goto.get(node << 8 | c)
        if nxt is None:
            found = None, NONE
        else:
            t = self.token[nxt]
            ends = t != NONE and (last == NONE or self._apart(last, t))
            found = self._open(last, nxt) if self.inner[nxt] else None, t if ends else NONE
        self.moves.setdefault(h, {})[c] = found
        self.moved += 1
        return found

    def _step(self, state: int, c: int) -> int:
        """Subset construction for one byte: all open hypotheses move, the one that finishes a token opens the next."""
        out, end, moves = [], NONE, self.moves
        for h in self.sets[state]:
            of = moves.get(h)
            found = of.get(c) if of is not None else None
            nxt, t = found or self._move(h, c)
            if nxt is not None:
                out.append(nxt)
            if end == NONE:
                end = t
        if end != NONE:
            h = self.fresh.get(end)
            if h is None:
                h = self.fresh[end] = self._open(end, 0)
            out.append(h)
        found = tuple(out)
        k = self.ids.get((found, end))
        if k is None:
            k = self.ids[found, end] = len(self.sets)
            self.sets.append(found)
            self.ends.append(end)
            if k >= len(self.over):
                self._room(2 * k)
            self.over[k] = end
        self.at[state << 8 | c] = k
        return k

    def word(self, b: bytes) -> tuple[int, ...]:
        """The tokens of one word (a match of the pattern)."""
        known = self.ranks.get(b)
        if known is not None:
            return (known,)
        self._bound()
        state, passed, at = 0, [0], self.at
        for c in b:
            key = state << 8 | c
            state = at[key]
            if not state:
                state = self._step(key >> 8, c)
                at = self.at
            passed.append(state)
        out, k, ends, text = [], len(b), self.ends, self.text
        while k > 0 and (t := ends[passed[k]]) != NONE:
            out.append(t)
            k -= len(text[t])
        if k:  # the ranks aren't closed under their own merges; merge this word directly
            return tuple(self.merge(b))
        out.reverse()
        return tuple(out)

    def _bound(self) -> None:
        if len(self.sets) > self.max_states or self.moved > 5 * self.max_states:
            self._reset()

    def _walk(self, data: np.ndarray, begins: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, where each word's begin, how many they are) of words, not empty, as pieces of data. All pass the states side by side."""
        out, first, count, size = [], np.zeros(len(begins), np.int64), np.zeros(len(begins), np.int64), 0
        order = np.argsort(-lengths, kind="stable")
        for b in range(0, len(order), 8192):
            self._bound()
            words = order[b : b + 8192]
            begin, length = begins[words], lengths[words]
            state, passed = np.zeros(len(words), np.int64), np.zeros((int(length[0]) + 1, len(words)), np.int32)
            for j in range(int(length[0])):
                m = int(np.searchsorted(-length, -j))  # longer ones stand first
                keys = state[:m] << 8 | data[begin[:m] + j]
                found = self.table[keys]
                if not found.all():
                    for key in np.unique(keys[found == 0]).tolist():
                        self._step(key >> 8, key & 255)
                    found = self.table[keys]
                state[:m] = passed[j + 1, :m] = found
            left, rest, tokens, rounds = length.copy(), np.arange(len(words)), [], []
            n = np.zeros(len(words), np.int64)
            broken = np.zeros(len(words), dtype=bool)
            while len(rest):
                t = self.over[passed[left[rest], rest]]
                broken[rest[t == NONE]] = True
                rest, t = rest[t != NONE], t[t != NONE]
                tokens.append(t)
                rounds.append(rest)
                n[rest] += 1
                left[rest] -= self.text.lengths[t]
                rest = rest[left[rest] > 0]
            direct = {k: self.merge(data[begin[k] : begin[k] + length[k]].tobytes()) for k in np.flatnonzero(broken).tolist()}
            for k, ids in direct.items():  # as in word()
                n[k] = len(ids)
            ends = np.cumsum(n)
            ids = np.zeros(int(ends[-1]), dtype=np.uint32)
            for r, (w, t) in enumerate(zip(rounds, tokens)):
                whole = ~broken[w]
                ids[ends[w[whole]] - 1 - r] = t[whole]
            for k, found in direct.items():
                ids[ends[k] - len(found) : ends[k]] = found
            first[words], count[words] = ends - n + size, n
            size += len(ids)
            out.append(ids)
        return np.concatenate(out) if out else np.empty(0, np.uint32), first, count

    def encode(self, text: str) -> list[int]:
        """The ids of a whole text."""
        return next(self.encode_all([text])).tolist()

    def encode_all(self, texts: Iterable[str | None]) -> Iterator[np.ndarray]:
        """The ids of each whole text, in order; GROUP characters and one text more are split at once."""
        group, size = [], 0
        for t in texts:
            group.append(t or "")
            size += len(group[-1])
            if size >= GROUP:
                yield from self._group(group)
                group, size = [], 0
        yield from self._group(group)

    def _group(self, texts: list[str]) -> Iterator[np.ndarray]:
        """Each different part of a group's texts is encoded once, and the texts are put together from these.

        Between two single spaces a text can be split on its own: a space belongs to what follows it. Only a space with
        white space on both sides, or at the end after white space, is matched together with its neighbours; such texts
        are split as a whole.
        """
        whole = [self.apart is None or bool(self.apart(t)) for t in texts]
        try:
            split = pa.array(["" if w else t for t, w in zip(texts, whole)], pa.large_string())
        except UnicodeEncodeError:  # lone surrogates
            whole = [True] * len(texts)
            split = pa.array([""] * len(texts), pa.large_string())
        lists = pc.split_pattern(split, " ")
        starts = lists.offsets.to_numpy()
        coded = lists.values.dictionary_encode()
        codes, chunks = coded.indices.to_numpy().astype(np.int64), coded.dictionary
        inner = np.ones(len(codes), dtype=bool)
        inner[starts[:-1]] = False  # what stands before a text's first space is encoded without one
        other = np.zeros(len(chunks), dtype=bool)
        other[codes[inner]] = True
        ids, first, count = self._letters(chunks, other)
        packed = [b""] * len(chunks)
        rest = np.flatnonzero(other)
        for k, c in zip(rest.tolist(), chunks.take(pa.array(rest)).to_numpy(zero_copy_only=False)):
            packed[k] = self._chunk(c)
        for t, w in zip(texts, whole):
            packed.append(b"".join(map(self._word, self.find(t if w else t.split(" ", 1)[0]))))
        lengths = np.fromiter(map(len, packed), np.int64, len(packed)) // 4
        begins = np.cumsum(lengths) - lengths + len(ids)
        ids = np.concatenate([ids, np.frombuffer(b"".join(packed), dtype="<u4").astype(np.uint32)])
        own = np.flatnonzero(count)
        begins[own], lengths[own] = first[own], count[own]
        codes[starts[:-1]] = np.arange(len(chunks), len(chunks) + len(texts))
        found = gather(ids, begins, lengths, codes)
        ends = np.concatenate([[0], np.cumsum(lengths[codes])])[starts]
        for k in range(len(texts)):
            yield found[ends[k] : ends[k + 1]]

    def _letters(self, chunks: pa.LargeStringArray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, where a chunk's begin, how many) of the wanted chunks that are letters, or letters and marks, after their space; they are wanted no more."""
        first, count = np.zeros(len(chunks), np.int64), np.zeros(len(chunks), np.int64)
        if not self.letters:
            return np.empty(0, np.uint32), first, count
        stems = pc.utf8_rtrim(chunks, MARKS)
        size = pc.binary_length(stems).to_numpy()
        fits = wanted & pc.utf8_is_alpha(stems).to_numpy(zero_copy_only=False) & (size < LONG)
        if self.unreached:
            fits &= ~pc.is_in(stems, value_set=pa.array(self.unreached, pa.large_string())).to_numpy(zero_copy_only=False)
        own = np.flatnonzero(fits)
        if not len(own):
            return np.empty(0, np.uint32), first, count
        wanted[own] = False
        words = stems.take(pa.array(own)).dictionary_encode()
        ids, begins, counts = self._walk(*flat_bytes(pc.binary_join_element_wise(pa.scalar(" ", pa.large_string()), words.dictionary, pa.scalar("", pa.large_string()))))
        data, at, length = flat_bytes(chunks)
        marks = length[own] - size[own]
        tail = gather(data, at[own] + size[own], marks, np.arange(len(own)))
        tails = pa.LargeStringArray.from_buffers(len(own), pa.py_buffer(np.concatenate([[0], np.cumsum(marks)]).astype(np.int64)), pa.py_buffer(tail)).dictionary_encode()
        packed = [self._word(m) if m else b"" for m in tails.dictionary.to_pylist()]
        sizes = np.fromiter(map(len, packed), np.int64, len(packed)) // 4
        flat = np.concatenate([ids, np.frombuffer(b"".join(packed), dtype="<u4").astype(np.uint32)])
        begins, counts = np.concatenate([begins, np.cumsum(sizes) - sizes + len(ids)]), np.concatenate([counts, sizes])
        pieces = np.stack([words.indices.to_numpy().astype(np.int64), tails.indices.to_numpy() + len(words.dictionary)], axis=1)
        count[own] = counts[pieces].sum(axis=1)
        first[own] = np.cumsum(count[own]) - count[own]
        return gather(flat, begins, counts, pieces.ravel()), first, count

    def _chunk(self, c: str) -> bytes:
        """The packed ids of a space and c, which stands before a space or the end."""
        ids = self.chunks.get(c)
        if ids is not None:
            return ids
        ids = self.older_chunks.get(c)
        if ids is None:
            ids = self._new(c)
        if len(c) <= 40:
            if len(self.chunks) >= self.max_chunks // 2:
                self.chunks, self.older_chunks = {}, self.chunks
            self.chunks[c] = ids
        return ids

    def _new(self, c: str) -> bytes:
        if self.letters:
            if c.isalpha():
                return self._tokens(" " + c)
            stem = c.rstrip(MARKS)
            if len(stem) < len(c) and stem.isalpha():
                return self._chunk(stem) + self._word(c[len(stem) :])  # the marks are a match of their own
            before, line, after = c.partition("\n")
            if line and before and after and not before[-1].isspace() and not after[0].isspace():
                return self._chunk(before) + self._word(line) + self._bare(after)  # so is a single line end
        return b"".join(map(self._word, self.find(" " + c)))

    def _bare(self, c: str) -> bytes:
        """The same without the space, at the beginning of a line."""
        if c.isalpha():
            return self._word(c)
        stem = c.rstrip(MARKS)
        if len(stem) < len(c) and stem.isalpha():
            return self._word(stem) + self._word(c[len(stem) :])
        return b"".join(map(self._word, self.find(c)))

    def _word(self, w: str) -> bytes:
        """The packed ids of a match."""
        ids = self.words.get(w)
        if ids is None:
            ids = self.older_words.get(w)
            if ids is None:
                ids = self._tokens(w)
            if len(w) <= 40:
                if len(self.words) >= self.max_words // 2:
                    self.words, self.older_words = {}, self.words
                self.words[w] = ids
        return ids

    def _tokens(self, w: str) -> bytes:
        return b"".join(map(self.packed.__getitem__, self.word(w.encode("utf-8", "surrogatepass"))))


def coder(ranks: bytes, pattern: str, **bounds: int) -> Transducer:
    """The worker's own transducer: tasks that follow in the same Python worker share its states and words. bounds: Transducer's."""
    key = ("bpe", hashlib.sha256(ranks).digest(), pattern, *sorted(bounds.items()))
    return worker_cache(key, lambda: Transducer(parse_ranks(ranks), pattern, **bounds))


#: Fixed values of UTF-8. By lead byte: (continuation bytes that follow, least and greatest value of the first of them).
LEADS = (
    {b: (1, 0x80, 0xBF) for b in range(0xC2, 0xE0)}
    | {0xE0: (2, 0xA0, 0xBF)} | {b: (2, 0x80, 0xBF) for b in (*range(0xE1, 0xED), 0xEE, 0xEF)} | {0xED: (2, 0x80, 0x9F)}
    | {0xF0: (3, 0x90, 0xBF)} | {b: (3, 0x80, 0xBF) for b in range(0xF1, 0xF4)} | {0xF4: (3, 0x80, 0x8F)}
)
#: The same values as one expression: characters with all their bytes, one after another.
WHOLE = re.compile(b"(?:[\x00-\x7f]++|" + b"|".join(b"[\\x%02x][\\x%02x-\\x%02x]" % (b, low, high) + b"[\x80-\xbf]" * (n - 1) for b, (n, low, high) in LEADS.items()) + b")++")
REPLACEMENT = "\ufffd"


class Utf8Stream:
    """Incremental UTF-8 decoding by a state machine: push() bytes, get the characters that they complete.

    The state is the open character: how many bytes it still lacks, between which values the next one must lie, and the
    bits so far. A byte that can't go on with it ends it as U+FFFD and is looked at again as a first byte; one that can't
    be a first byte is U+FFFD itself. Runs of characters with all their bytes are taken whole while none is open.
    """

    def __init__(self) -> None:
        self.lacks, self.low, self.high, self.bits = 0, 0, 0, 0

    def push(self, data: bytes) -> str:
        if not self.lacks and data.isascii():
            return data.decode("ascii")
        lacks, low, high, bits = self.lacks, self.low, self.high, self.bits
        out, k, n = [], 0, len(data)
        while k < n:
            c = data[k]
            if lacks:
                if low <= c <= high:
                    bits, lacks, low, high = bits << 6 | c & 0x3F, lacks - 1, 0x80, 0xBF
                    if not lacks:
                        out.append(chr(bits))
                    k += 1
                else:
                    out.append(REPLACEMENT)
                    lacks = 0
            elif run := WHOLE.match(data, k):
                out.append(run.group().decode("utf-8"))
                k = run.end()
            else:
                if c in LEADS:
                    lacks, low, high = LEADS[c]
                    bits = c & (0x3F >> lacks)
                else:
                    out.append(REPLACEMENT)
                k += 1
        self.lacks, self.low, self.high, self.bits = lacks, low, high, bits
        return "".join(out)

    def close(self) -> str:
        """What the end of the stream leaves: U+FFFD for an open character."""
        rest, self.lacks = REPLACEMENT if self.lacks else "", 0
        return rest


class Tokens(dict):
    """Bytes by id, and the bytes of a run of ids. The ids are few and small enough for a table."""

    def __init__(self, text: dict[int, bytes]) -> None:
        super().__init__(text)
        self.lengths = np.zeros(max(self, default=NONE) + 1, dtype=np.int64)
        for i, b in self.items():
            self.lengths[i] = len(b)
        self.begins = np.cumsum(self.lengths) - self.lengths
        self.flat = np.frombuffer(b"".join(self[i] for i in sorted(self)), dtype=np.uint8)

    def join(self, ids: np.ndarray) -> bytes:
        return gather(self.flat, self.begins, self.lengths, ids).tobytes()


def decode_stream(ids: Iterable[int], text: dict[int, bytes], block: int = 4096) -> Iterator[tuple[bytes, str]]:
    """Blocks of (bytes, characters completed by them)."""
    stream, known = Utf8Stream(), isinstance(text, Tokens)
    ids = np.asarray(ids if isinstance(ids, np.ndarray) else list(ids), dtype=np.int64) if known else list(ids)
    for k in range(0, len(ids), block):
        part = ids[k : k + block]
        data = text.join(part) if known else b"".join(map(text.__getitem__, part))
        yield data, stream.push(data)
    if rest := stream.close():
        yield b"", rest


#: Rows whose ids are held at once.
SLICE = 512


def sliced(batches: Iterator[pa.RecordBatch], rows: int = SLICE) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of `rows` at most; an empty batch stays one."""
    for batch in batches:
        for k in range(0, max(1, batch.num_rows), rows):
            yield batch.slice(k, rows)


def encode(df: DataFrame, ranks: bytes, pattern: str, text: str = "text", out: str = "ids") -> DataFrame:
    """Add the token ids of each whole text; a null or empty text has none. Narrow: no shuffle, rows stay in place.

    ranks: the content of a rank file. pattern: each match is encoded on its own. A text with lone surrogates can't
    occur in Spark strings. An existing column named `out` is replaced.
    """
    schema = _with(df.drop(out), f"{out} array<int>")
    keep = [c for c in df.columns if c != out]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(ranks, pattern)
        for batch in sliced(batches):
            ids = [x.astype(np.int32) for x in own.encode_all(batch.column(text).to_pylist())]
            ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
            flat = np.concatenate(ids) if ids else np.empty(0, np.int32)
            column = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), column], [*keep, out])

    return df.mapInArrow(without_gc(run), schema)


def decode(df: DataFrame, ranks: bytes, ids: str = "ids", out: str = "decoded") -> DataFrame:
    """Add the bytes of the ids as column `out`, and whether they are valid UTF-8 as `<out>_valid`. Null ids: empty."""
    keep = [c for c in df.columns if c not in (out, f"{out}_valid")]
    schema = _with(df.select(*keep), f"{out} binary", f"{out}_valid boolean")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        text = Tokens({i: b for b, i in parse_ranks(ranks).items()})
        for batch in batches:
            data, valid = [], []
            for row in batch.column(ids):
                parts = list(decode_stream((row.values.to_numpy(zero_copy_only=False) if row.is_valid else ()), text))
                whole = b"".join(p[0] for p in parts)
                data.append(whole)
                valid.append(len("".join(p[1] for p in parts).encode()) == len(whole))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(data, pa.binary()), pa.array(valid)], [*keep, out, f"{out}_valid"])

    return df.mapInArrow(without_gc(run), schema)


def checked(df: DataFrame, ranks: bytes, pattern: str, text: str = "text", **bounds: int) -> DataFrame:
    """df with columns `ids` and `round_trip`: whether streaming decode of the ids gives the text. Null texts: no ids, true.

    bounds: of the transducer's memo tables (max_states, max_words, max_chunks); they bound memory and change no result.
    Rows go out in parts of SLICE, so that the ids of a whole batch are never held at once.
    """
    keep = [c for c in df.columns if c not in ("ids", "round_trip")]
    schema = _with(df.select(*keep), "ids array<int>", "round_trip boolean")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(ranks, pattern, **bounds)
        for batch in sliced(batches):
            ids, same = [], []
            texts = batch.column(text).to_pylist()
            for t, found in zip(texts, own.encode_all(texts)):
                ids.append(found.astype(np.int32))
                same.append("".join(chars for _, chars in decode_stream(found, own.text)) == (t or ""))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(ids, pa.list_(pa.int32())), pa.array(same)], [*keep, "ids", "round_trip"])

    return df.mapInArrow(without_gc(run), schema)


def _with(df: DataFrame, *more: str) -> str:
    return ", ".join([*(f"`{n}` {t}" for n, t in df.dtypes), *more])


def digest(df: DataFrame, ranks: bytes, pattern: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of each row of (doc_id, text): encode, then decode, in one pass.

    The same transducer and streaming decoder as encode() and decode(); the ids don't travel between them.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(ranks, pattern)
        for batch in batches:
            counts, of_ids, of_text = [], [], []
            for ids in own.encode_all(batch.column("text").to_pylist()):
                counts.append(len(ids))
                of_ids.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                sha = hashlib.sha256()
                for data, _ in decode_stream(ids, own.text):
                    sha.update(data)
                of_text.append(sha.hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = dict(df.dtypes)["doc_id"]
    return df.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(without_gc(run), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
