"""Byte-level BPE over many texts at once.

Texts repeat most of their words, so a chunk of texts is split into words with array operations, its
distinct words are encoded once (and remembered), and ids are gathered back.  The splitting rule is
that of the byte-level pattern in the vocabulary's package; texts with characters outside the stable
ranges below go through ``tokenizers`` whole.  Results equal ``tokenizers`` on every text.
"""

from __future__ import annotations

import base64
import os

import numpy as np

_LETTER, _NUMBER, _SPACE, _OTHER, _END, _RARE = 1, 2, 3, 4, 5, 6
_TABLE = 0x2100
#: Ranges of code points whose letter, number and space classes no Unicode version moves.
_STABLE = ((0x01, 0x377), (0x400, 0x52F), (0x2000, 0x2064))
_MEMORY = 1_500_000


def _classes() -> np.ndarray:
    import regex

    table = np.full(_TABLE + 1, _RARE, np.uint8)
    letter, number, space = regex.compile(r"\p{L}"), regex.compile(r"\p{N}"), regex.compile(r"\s")
    for low, high in _STABLE:
        for c in range(low, high + 1):
            x = chr(c)
            table[c] = _LETTER if letter.match(x) else _NUMBER if number.match(x) else _SPACE if space.match(x) else _OTHER
    # Separators that regular-expression engines class differently.
    table[[0x1C, 0x1D, 0x1E, 0x1F, 0x85, 0x180E & 0x1FFF]] = _RARE
    return table


class Encoder:
    """Encodes lists of texts to one id array and offsets."""

    def __init__(self, ranks_path: str, json_path: str, pattern: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import tiktoken

        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self._fast = tiktoken.Encoding("distinct_words", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self._json_path, self._slow = json_path, None
        self._bytes_of = np.zeros(max(ranks.values()) + 2, np.int64)
        for token, i in ranks.items():
            self._bytes_of[i] = len(token)
        self._class = _classes()
        draw = np.random.default_rng(7)
        self._value = draw.integers(1, 1 << 63, _TABLE + 1, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self._base = int(draw.integers(1 << 40, 1 << 62)) * 2 + 1
        self._powers = self._inverses = np.zeros(0, np.uint64)
        self._runs: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []

    def _grow(self, n: int) -> None:
        if n > len(self._powers):
            n = max(n, 1 << 16)
            for name, base in (("_powers", self._base), ("_inverses", pow(self._base, -1, 1 << 64))):
                steps = np.full(n, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.multiply.accumulate(steps))

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and where each text's ids begin (one more entry than texts)."""
        joined = "\0".join(texts) + "\0"
        points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        kinds = self._class[np.minimum(points, _TABLE)]
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        ends = np.cumsum(lengths + 1) - 1
        kinds[ends] = _END
        rare = np.flatnonzero(kinds == _RARE)
        slow = np.unique(np.searchsorted(ends, rare)) if len(rare) else rare
        starts = self._split(points, kinds)
        counts, pieces = self._look_up(joined, points, kinds, starts)
        whose = np.searchsorted(ends, starts)
        if len(slow):
            keep = ~np.isin(whose, slow)
            pieces, counts_kept = _take(pieces, counts, keep)
            whose, counts = whose[keep], counts_kept
        per = np.bincount(whose, weights=counts, minlength=len(texts)).astype(np.int64)
        if not len(slow):
            return pieces, np.concatenate(([0], np.cumsum(per)))
        found = {int(i): np.asarray(self._whole(texts[i]), np.uint32) for i in slow}
        bounds = np.concatenate(([0], np.cumsum(per)))
        parts = [found.get(i, pieces[bounds[i] : bounds[i + 1]]) for i in range(len(texts))]
        return np.concatenate(parts) if parts else pieces, np.concatenate(([0], np.cumsum([len(x) for x in parts]))).astype(np.int64)

    def _whole(self, text: str) -> list[int]:
        if self._slow is None:
            from tokenizers import Tokenizer

            self._slow = Tokenizer.from_file(self._json_path)
            self._slow.encode_special_tokens = True
        return self._slow.encode(text, add_special_tokens=False).ids

    @staticmethod
    def _split(points: np.ndarray, kinds: np.ndarray) -> np.ndarray:
        """Where words begin.  The last blank before a word joins it, if it is a plain space; an apostrophe takes its ending along."""
        begins = np.empty(len(points), bool)
        begins[0] = True
        np.not_equal(kinds[1:], kinds[:-1], out=begins[1:])
        begins |= kinds == _END
        word_next = np.flatnonzero((kinds[:-1] == _SPACE) & (kinds[1:] != _SPACE) & (kinds[1:] != _END))
        begins[word_next] = True
        begins[word_next[points[word_next] == 32] + 1] = False
        quote = np.flatnonzero((points[:-3] == 39) & begins[:-3] & (kinds[1:-2] == _LETTER)) if len(points) > 3 else np.zeros(0, np.int64)
        if len(quote):
            a, b = points[quote + 1], points[quote + 2]
            short = np.isin(a, [ord(x) for x in "stmd"])
            double = ((b == ord("e")) & ((a == ord("r")) | (a == ord("v")))) | ((a == ord("l")) & (b == ord("l")))
            begins[quote[short | double] + 1] = False
            after = quote[short] + 2
            begins[after] |= kinds[after] == _LETTER
            after = quote[double & ~short] + 3
            begins[after] |= kinds[after] == _LETTER
        starts = np.flatnonzero(begins)
        return starts[kinds[starts] != _END]

    def _look_up(self, joined: str, points: np.ndarray, kinds: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(starts):
            return np.zeros(0, np.int64), np.zeros(0, np.uint32)
        n = len(points)
        self._grow(n)
        after = np.append(starts[1:], n)
        separators = np.flatnonzero(kinds == _END)
        after = np.minimum(after, separators[np.searchsorted(separators, starts)])
        mixed = self._value[np.minimum(points, _TABLE)] * self._powers[:n]
        running = np.concatenate((np.zeros(1, np.uint64), np.cumsum(mixed, dtype=np.uint64)))
        keys = (running[after] - running[starts]) * self._inverses[starts]
        keys ^= keys >> np.uint64(29)
        distinct, first, back = np.unique(keys, return_index=True, return_inverse=True)
        counts, ids = self._encode_distinct(distinct, joined, kinds, starts[first], after[first])
        offsets = np.concatenate(([0], np.cumsum(counts)))
        return counts[back], _gather(ids, offsets, counts, back)

    def _encode_distinct(self, keys: np.ndarray, joined: str, kinds: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        counts, sources = np.zeros(len(keys), np.int64), []
        unknown = np.ones(len(keys), bool)
        for r, (known, offsets, sizes, ids) in enumerate(self._runs):
            at = np.minimum(np.searchsorted(known, keys), len(known) - 1)
            hit = unknown & (known[at] == keys)
            unknown &= ~hit
            counts[hit] = sizes[at[hit]]
            sources.append((np.flatnonzero(hit), _gather(ids, offsets, sizes, at[hit])))
        new = np.flatnonzero(unknown)
        if len(new):
            sizes, ids = self._encode_words([joined[i:j] for i, j in zip(a[new].tolist(), b[new].tolist(), strict=True)], kinds[b[new] - 1] == _SPACE)
            counts[new] = sizes
            sources.append((new, ids))
            self._remember(keys[new], sizes, ids)
        out, offsets = np.empty(int(counts.sum()), np.uint32), np.concatenate(([0], np.cumsum(counts)))
        for which, ids in sources:
            out[_spread(offsets[which], counts[which])] = ids
        return counts, out

    def _encode_words(self, words: list[str], blank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct words, apart from blanks, are encoded as lines of one text: a line break stays a word of its own."""
        sizes, parts = np.zeros(len(words), np.int64), [np.zeros(0, np.uint32)] * len(words)
        for i in np.flatnonzero(blank).tolist():
            parts[i] = np.asarray(self._fast.encode_ordinary(words[i]), np.uint32)
            sizes[i] = len(parts[i])
        plain = np.flatnonzero(~blank)
        if len(plain):
            chosen = [words[i] for i in plain.tolist()]
            ids = np.asarray(self._fast.encode_ordinary("\n".join(chosen)), np.uint32)
            byte_ends = np.cumsum(self._bytes_of[ids])
            word_ends = np.cumsum(np.fromiter((len(x.encode()) + 1 for x in chosen), np.int64, len(chosen))) - 1
            stop = np.searchsorted(byte_ends, word_ends) + 1
            begin = np.concatenate(([0], stop[:-1] + 1))
            sizes[plain] = stop - begin
        offsets = np.concatenate(([0], np.cumsum(sizes)))
        out = np.empty(int(offsets[-1]), np.uint32)
        if len(plain):
            out[_spread(offsets[plain], sizes[plain])] = ids[_spread(begin, sizes[plain])]
        for i in np.flatnonzero(blank).tolist():
            out[offsets[i] : offsets[i + 1]] = parts[i]
        return sizes, out

    def _remember(self, keys: np.ndarray, sizes: np.ndarray, ids: np.ndarray) -> None:
        self._runs.append((keys, np.concatenate(([0], np.cumsum(sizes))), sizes, ids))
        if sum(len(r[0]) for r in self._runs) > _MEMORY:
            self._runs = self._runs[-1:]
        while len(self._runs) > 1 and len(self._runs[-1][0]) * 3 > len(self._runs[-2][0]):
            (k1, o1, s1, i1), (k2, _, s2, i2) = self._runs[-2:]
            keys, sizes, ids = np.concatenate((k1, k2)), np.concatenate((s1, s2)), np.concatenate((i1, i2))
            order, offsets = np.argsort(keys), np.concatenate(([0], np.cumsum(sizes)))
            ids = _gather(ids, offsets, sizes, order)
            self._runs[-2:] = [(keys[order], np.concatenate(([0], np.cumsum(sizes[order]))), sizes[order], ids)]


def _spread(begin: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """begin[0], begin[0]+1, ... for sizes[0] places, then the same from begin[1], and so on."""
    total = int(sizes.sum())
    shift = np.repeat(begin - np.concatenate(([0], np.cumsum(sizes)[:-1])), sizes) if len(sizes) else np.zeros(0, np.int64)
    return np.arange(total) + shift


def _gather(ids: np.ndarray, offsets: np.ndarray, sizes: np.ndarray, which: np.ndarray) -> np.ndarray:
    return ids[_spread(offsets[which], sizes[which])]


def _take(ids: np.ndarray, counts: np.ndarray, keep: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return ids[np.repeat(keep, counts)], counts[keep]
