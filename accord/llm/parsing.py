"""Order of all suffixes of a set of texts, by prefix-free parsing.

A rolling hash over GRAM bytes that is 0 modulo MODULUS is a trigger; a phrase runs from one trigger to the end of the next, so neighbours overlap by GRAM bytes and,
but at the ends of texts, none is the beginning of another. The dictionary has each phrase once, the parse has the texts as phrase numbers. Suffixes of the dictionary
are ranked by doubling, suffixes of the parse likewise, and the order of the texts' suffixes follows from the two: first the rank of what is left of the
phrase, then the rank of the parse behind it. Texts that repeat each other share phrases, so the work goes with the dictionary, not with the texts.

Comparisons are on bytes, not on hashes. A suffix ends with its text: of two of which one begins the other, the shorter comes first; equal ones are in any order.
"""

from __future__ import annotations

import numpy as np

#: Bytes of the rolling hash, and the modulus that makes a trigger.
GRAM, MODULUS = 12, 24
_BASE = np.uint64(0x9E3779B97F4A7C15)


def _grams(data: np.ndarray) -> np.ndarray:
    """The rolling hash at each place that has GRAM bytes."""
    n = len(data) - GRAM + 1
    h = np.zeros(max(n, 0), np.uint64)
    with np.errstate(over="ignore"):
        for k in range(GRAM if n > 0 else 0):
            h = h * _BASE + data[k : k + n] + np.uint64(1)
        h ^= h >> np.uint64(31)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        return h >> np.uint64(33)


class _Ranks:
    """Ranks of all suffixes of strings that lie one after another, each followed by one end mark; symbols are positive. Level k ranks by the first
    sizes[k] symbols; equal beginnings have equal ranks."""

    def __init__(self, symbols: np.ndarray, ends: np.ndarray, first: tuple[int, np.ndarray]) -> None:
        self.ends = ends  # for each place that of its string's end mark
        n, here = len(symbols), np.arange(len(symbols))
        size, key = first
        self.sizes, self.levels = [], []
        longest = int((ends - here).max(initial=0))
        while True:
            found, rank = np.unique(key, return_inverse=True)
            self.sizes.append(size)
            self.levels.append(rank)
            if size >= longest or len(found) == n:
                break
            key = rank.astype(np.int64) * (n + 1) + rank[np.minimum(here + size, ends)]
            size *= 2
        self.symbols = symbols

    @property
    def last(self) -> np.ndarray:
        return self.levels[-1]

    def common(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """How many symbols from a and from b on are the same, up to the end of a string."""
        a, b = a.copy(), b.copy()
        out = np.zeros(len(a), np.int64)
        room = np.minimum(self.ends[a] - a, self.ends[b] - b)

        def take(same: np.ndarray, size: int) -> None:
            out[same] += size
            a[same] += size
            b[same] += size

        for size, rank in zip(reversed(self.sizes), reversed(self.levels), strict=True):
            while True:  # the largest size may fit more than once, where ranks were all different early
                same = (out + size <= room) & (a != b)
                same[same] = rank[a[same]] == rank[b[same]]
                if not same.any():
                    break
                take(same, size)
                if size != self.sizes[-1]:
                    break
        for _ in range(self.sizes[0] - 1):
            same = out < room
            same[same] = self.symbols[a[same]] == self.symbols[b[same]]
            if not same.any():
                break
            take(same, 1)
        return np.where(a == b, room, out)


def suffix_order(texts: list[bytes], least: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, offset, lcp) of all suffixes of at least so many bytes, in order; lcp is how many bytes each has in common with the one before it."""
    lengths = np.array([len(t) for t in texts], np.int64)
    data = np.frombuffer(b"".join(texts), np.uint8)
    starts = np.cumsum(lengths) - lengths
    owner = np.repeat(np.arange(len(texts)), lengths)
    if not len(data):
        return (np.zeros(0, np.int64),) * 3

    hits = np.nonzero(_grams(data) % np.uint64(MODULUS) == 0)[0]
    hits = hits[owner[hits] == owner[hits + GRAM - 1]] if len(hits) else hits  # none across two texts
    heads = np.unique(np.concatenate([starts[lengths > 0], hits]))  # where phrases begin
    whose = owner[heads]
    final = np.append(whose[1:] != whose[:-1], True)  # the last phrase of its text
    tails = np.where(final, starts[whose] + lengths[whose], np.append(heads[1:], 0) + GRAM)

    raw = data.tobytes()
    slices = [raw[a:b] for a, b in zip(heads.tolist(), tails.tolist())]
    words = sorted(set(slices))
    number = {w: i for i, w in enumerate(words)}
    parse = np.array([number[w] for w in slices], np.int64)

    # the dictionary: its phrases one after another, each followed by an end mark
    sizes = np.array([len(w) for w in words], np.int64) + 1
    at = np.cumsum(sizes) - sizes
    symbols = np.zeros(int(sizes.sum()), np.int64)
    inner = np.ones(len(symbols), bool)
    inner[at + sizes - 1] = False
    symbols[inner] = np.frombuffer(b"".join(words), np.uint8).astype(np.int64) + 1
    ends = np.repeat(at + sizes - 1, sizes)
    here = np.arange(len(symbols))
    key = np.zeros(len(symbols), np.int64)
    for k in range(7):  # seven bytes and end marks fit a whole number
        key = key * 257 + symbols[np.minimum(here + k, ends)]
    dictionary = _Ranks(symbols, ends, (7, key))

    # the parse: phrase numbers, an end mark behind each text
    places = np.arange(len(parse)) + np.cumsum(final) - final
    marked = np.zeros(len(parse) + int(final.sum()), np.int64)
    marked[places] = parse + 1
    stops = places[final] + 1
    parse_ends = stops[np.searchsorted(stops, np.arange(len(marked)))]
    parsed = _Ranks(marked, parse_ends, (1, marked))

    # the texts: what is left of the phrase, then the parse behind it
    left = np.repeat(starts + lengths, lengths) - np.arange(len(data))
    spots = np.nonzero(left >= least)[0]
    phrase = np.searchsorted(heads, spots, side="right") - 1
    in_dictionary = at[parse[phrase]] + spots - heads[phrase]
    behind = np.where(final[phrase], places[phrase] + 1, places[np.minimum(phrase + 1, len(parse) - 1)])
    order = np.argsort(dictionary.last[in_dictionary].astype(np.int64) * (len(marked) + 1) + parsed.last[behind], kind="stable")

    spots, phrase, in_dictionary = spots[order], phrase[order], in_dictionary[order]
    lcp = np.zeros(len(spots), np.int64)
    if len(spots) > 1:
        a, b = in_dictionary[:-1], in_dictionary[1:]
        same = dictionary.last[a] == dictionary.last[b]
        lcp[1:] = dictionary.common(a, b)
        # equal to the end of the phrase: on through equal phrases behind, then into the first two that differ
        i, j = phrase[:-1][same], phrase[1:][same]
        more = ~final[i] & ~final[j]
        rows = np.nonzero(same)[0][more]
        i, j = i[more] + 1, j[more] + 1
        equal = parsed.common(places[i], places[j])
        i, j = i + equal, j + equal
        over = (i >= len(parse)) | (j >= len(parse))
        i, j = np.minimum(i, len(parse) - 1), np.minimum(j, len(parse) - 1)
        p, q = spots[:-1][rows], spots[1:][rows]
        over |= (owner[heads[i]] != owner[p]) | (owner[heads[j]] != owner[q])
        tail = np.zeros(len(i), np.int64)
        tail[~over] = dictionary.common(at[parse[i[~over]]], at[parse[j[~over]]])
        lcp[1 + rows] = np.where(over, len(data), heads[i] - p + tail)
        lcp[1:] = np.minimum(lcp[1:], np.minimum(left[spots[:-1]], left[spots[1:]]))
    return owner[spots], spots - starts[owner[spots]], lcp


def repeated(texts: list[bytes], window: int) -> tuple[np.ndarray, np.ndarray]:
    """(text, offset) of all strings of so many bytes that start at two places or more."""
    text, offset, lcp = suffix_order(texts, window)
    again = lcp >= window
    met = again | np.append(again[1:], False) if len(again) else again
    return text[met], offset[met]
