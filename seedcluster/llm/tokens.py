"""Byte-level BPE over Arrow batches: pre-tokens found with array operations, their ids kept in a bounded cache.

The cut into pre-tokens is the published pattern of byte-level BPE, applied to code points of known class. It is cut anew
for each chunk of a text; chunks overlap, and the boundaries of two chunks are joined where both have the same one, since
from a boundary on the pattern looks only forward.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa

from .common import CLEARED, chunks, spans_hash

OTHER, LETTER, NUMBER, SPACE = 0, 1, 2, 3
#: The endings that stand alone behind an apostrophe in the pattern (fixed values).
ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")
PATTERNS = {LETTER: r"\p{L}", NUMBER: r"\p{N}", SPACE: r"\s"}


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(4)
def classes(library: str) -> np.ndarray:
    """The class of each code point, asked of the library itself, so that its Unicode version holds."""
    points = [*range(0xD800), *range(0xE000, 0x110000)]
    every = "".join(map(chr, points))
    out = np.zeros(0x110000, np.uint8)
    for kind, pattern in PATTERNS.items():
        if library == "tiktoken":
            import tiktoken

            got = bytes(tiktoken.Encoding("class", pat_str=pattern, mergeable_ranks={bytes([i]): i for i in range(256)}, special_tokens={}).encode_ordinary(every)).decode()
        else:
            from tokenizers import Regex, pre_tokenizers

            got = "".join(x for x, _ in pre_tokenizers.Split(Regex(f"{pattern}+"), "removed", invert=True).pre_tokenize_str(every))
        out[np.frombuffer(got.encode("utf-32-le"), np.uint32)] = kind
    return out


def pretokens(points: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Where pre-tokens start, over rows points[offsets[i]:offsets[i+1]] laid end to end. No pre-token crosses rows."""
    n = len(points)
    if not n:
        return np.zeros(0, np.int64)
    kind = table[points]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    new = np.ones(n + 1, bool)
    new[1:n] = kind[1:] != kind[:-1]
    new |= edge
    start = new.copy()
    # White space before something else gives up its last character: a blank leads the next pre-token, another stands alone.
    before = np.flatnonzero(new[1:n] & ~edge[1:n] & (kind[:-1] == SPACE)) + 1
    start[before - 1] = True
    blank = before[points[before - 1] == 32]
    start[blank] = False
    quote = np.flatnonzero((points == 39) & start[:n])
    if len(quote):
        at = lambda k: np.where(quote + k < n, points[np.minimum(quote + k, n - 1)], 0)
        inside = lambda k: quote + k < offsets[np.searchsorted(offsets, quote, "right")]
        one, two = at(1), at(2)
        for ending in ENDINGS:
            k = len(ending)
            hit = (one == ord(ending[0])) & inside(1)
            if k == 2:
                hit &= (two == ord(ending[1])) & inside(2)
            q = quote[hit]
            start[q + 1] = False
            start[q + 1 + k] = True
    return np.flatnonzero(start[:n])


def chunked_pretokens(points: np.ndarray, table: np.ndarray, chunk: int = 1 << 20, overlap: int = 1 << 10) -> np.ndarray:
    """pretokens() of one long row by overlapping chunks; cut() of each chunk may run anywhere."""
    parts = [(a, cut(points[a : a + chunk + overlap], a + chunk + overlap >= len(points), table)) for a in range(0, max(len(points), 1), chunk)]
    return stitch(points, parts, table)


def rows_in_chunks(points: np.ndarray, offsets: np.ndarray, table: np.ndarray, chunk: int, overlap: int) -> tuple[np.ndarray, np.ndarray]:
    """pretokens() of many rows, each by overlapping chunks of its own that are stitched; and how many chunks each row has. All chunks are cut side by side."""
    size = np.diff(offsets)
    count = np.maximum(1, -(-size // chunk))
    row = np.repeat(np.arange(len(size)), count)
    no = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
    first = offsets[row] + no * chunk
    end = np.minimum(first + chunk + overlap, offsets[row + 1])
    at = np.concatenate([[0], np.cumsum(end - first)])
    got = pretokens(points[np.arange(at[-1]) + np.repeat(first - at[:-1], end - first)], at, table)
    cuts = np.searchsorted(got, at)
    here = got + np.repeat(first - at[:-1], np.diff(cuts))
    out = [here[np.repeat(count[row] == 1, np.diff(cuts))]]
    head = np.cumsum(count) - count
    settled = np.where(end < offsets[row + 1], 1, 0)  # a pre-token that touches its chunk's end may go on
    for r in np.flatnonzero(count > 1).tolist():
        a = int(offsets[r])
        parts = [((k - head[r]) * chunk, here[cuts[k] : cuts[k + 1] - settled[k]] - first[k]) for k in range(head[r], head[r] + count[r])]
        out.append(stitch(points[a : offsets[r + 1]], parts, table) + a)
    return np.sort(np.concatenate(out)), count


def cut(piece: np.ndarray, ends: bool, table: np.ndarray) -> np.ndarray:
    """Boundaries in a chunk that its own text settles: a pre-token that touches the chunk's end may go on, unless the text ends."""
    got = pretokens(piece, np.array([0, len(piece)]), table)
    return got if ends else got[:-1]


def stitch(points: np.ndarray, parts: list[tuple[int, np.ndarray]], table: np.ndarray) -> np.ndarray:
    """Joins the chunks' boundaries at the first one that a chunk shares with those before it."""
    out = np.zeros(0, np.int64)
    for i, (at, got) in enumerate(parts):
        got = got + at
        if not i:
            out = got
            continue
        both = np.intersect1d(out[np.searchsorted(out, at) :], got, assume_unique=True)
        if len(both):
            out = np.concatenate([out[out < both[0]], got[got >= both[0]]])
            continue
        # No shared boundary in the overlap: go on from the last settled one until the chunk agrees.
        last = int(out[-1]) if len(out) else 0
        width = max(at - last, 1)
        while True:
            width *= 2
            end = min(last + width, len(points))
            own = cut(points[last:end], end == len(points), table) + last
            both = np.intersect1d(own[own > last], got, assume_unique=True)
            if len(both) or end == len(points):
                break
        join = both[0] if len(both) else len(points)
        out = np.concatenate([out[out < last], own[own < join], got[got >= join]])
    return out


class Encoder:
    """ids of whole texts. Pre-tokens met before are looked up by hash in tables of a fixed size; the others go to the library."""

    WIDTH = 6
    #: Room behind the table for the ids of a chunk's new pre-tokens.
    TAIL = 1 << 20

    def __init__(self, library: str, path: str, slots: int = 1 << 21):
        self.library, self.table, self.slots = library, classes(library), slots
        self.added, self.find_added = {}, None
        self.keys, self.count, self.ids = np.zeros(slots, np.uint64), np.zeros(slots, np.uint8), np.zeros(slots * self.WIDTH + self.TAIL, np.uint16)
        if library == "tiktoken":
            import base64

            import public_tokenizers
            import tiktoken

            with open(path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.tool = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
            self.bytes = np.array([x for x, _ in sorted(ranks.items(), key=lambda x: x[1])], object)
        else:
            from tokenizers import Tokenizer, pre_tokenizers

            self.tool = Tokenizer.from_file(path)
            self.model = self.tool.model
            with open(path) as f:
                added = json.load(f)["added_tokens"]
            if any(x["single_word"] or x["lstrip"] or x["rstrip"] for x in added):
                raise ValueError("added tokens that take spaces or whole words only are not supported")
            self.added = {x["content"]: x["id"] for x in added}
            self.find_added = re.compile("|".join(re.escape(x) for x in sorted(self.added, key=len, reverse=True))) if added else None
            level = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
            low = {i: level.pre_tokenize_str(chr(i))[0][0] for i in range(128)}
            high = {b: level.pre_tokenize_str(c)[0][0][i] for c in map(chr, [*range(0x80, 0x800), *range(0x800, 0xD800, 64), *range(0x10000, 0x110000, 4096)]) for i, b in enumerate(c.encode())}
            self.letters = low | high

    def _asked(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """How many ids each piece has, and all ids. A pre-token needs the library's model only, in the letters that stand for bytes."""
        if self.library == "tiktoken":
            got = [self.tool.encode_ordinary(x) for x in pieces]
        else:
            ask, letters = self.model.tokenize, self.letters
            got = [[t.id for t in ask(x.encode().decode("latin-1").translate(letters))] for x in pieces]
        return np.fromiter(map(len, got), np.int64, len(got)), np.fromiter((i for x in got for i in x), np.uint16)

    def encode(self, points: np.ndarray, offsets: np.ndarray, most: int = 500_000) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the rows, and how many each row has. An added token's content is that token, and text ends and begins there."""
        found = self._found(points, offsets)
        if found:
            start, end, one = (np.array(x) for x in zip(*found, strict=True))
            edges = np.unique(np.concatenate([offsets, start, end]))
            inside = np.isin(edges[:-1], start)
            cut = np.diff(edges) * ~inside
            keep = np.repeat(~inside, np.diff(edges))
            ids, n = self.encode_plain(points[keep], np.concatenate([[0], np.cumsum(cut)]), most)
            ids = np.insert(ids, np.concatenate([[0], np.cumsum(n)])[np.flatnonzero(inside)], one)
            total = np.concatenate([[0], np.cumsum(n + inside)])
            return ids, np.diff(total[np.searchsorted(edges, offsets)])
        return self.encode_plain(points, offsets, most)

    def _found(self, points: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int]]:
        """(first, end, id) of the added tokens in the rows."""
        if not self.added or not len(points):
            return []
        at = np.unique(np.concatenate([np.flatnonzero((points[: len(points) - len(x) + 1] == ord(x[0])) & (points[len(x) - 1 :] == ord(x[-1]))) for x in self.added if len(x) <= len(points)] or [np.zeros(0, np.int64)]))
        rows = np.unique(np.searchsorted(offsets, at, "right") - 1).tolist()
        texts = ((int(offsets[r]), points[offsets[r] : offsets[r + 1]].astype("<u4").tobytes().decode("utf-32-le")) for r in rows)
        return [(a + m.start(), a + m.end(), self.added[m[0]]) for a, text in texts for m in self.find_added.finditer(text)]

    def encode_plain(self, points: np.ndarray, offsets: np.ndarray, most: int = 500_000) -> tuple[np.ndarray, np.ndarray]:
        """The same for text without added tokens."""
        got = [self._chunk(points[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in chunks(np.diff(offsets), most)]
        return (np.concatenate([x for x, _ in got]), np.concatenate([n for _, n in got])) if got else (np.zeros(0, np.uint16), np.zeros(0, np.int64))

    def _chunk(self, points: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        rows = len(offsets) - 1
        if not len(points):
            return np.zeros(0, np.uint16), np.zeros(rows, np.int64)
        starts = pretokens(points, offsets, self.table) if rows > 1 else chunked_pretokens(points, self.table)
        out, total = self._ids(points, starts)
        at_row = np.concatenate([[0], total])[np.searchsorted(starts, offsets)]
        return out, np.diff(at_row)

    def encode_cut(self, points: np.ndarray, offsets: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids of rows whose pre-tokens are known, and how many each row has."""
        if not len(points):
            return np.zeros(0, np.uint16), np.zeros(len(offsets) - 1, np.int64)
        out, total = self._ids(points, starts)
        return out, np.diff(np.concatenate([[0], total])[np.searchsorted(starts, offsets)])

    def pieces(self, points: np.ndarray, starts: np.ndarray, most: int = 100_000) -> tuple[np.ndarray, int]:
        """ids of one text whose pre-tokens are known, and how many."""
        got = []
        for a in range(0, len(starts), most):
            part = starts[a : a + most]
            end = int(starts[a + most]) if a + most < len(starts) else len(points)
            got.append(self._ids(points[part[0] : end], part - part[0])[0])
        out = np.concatenate(got) if got else np.zeros(0, np.uint16)
        return out, len(out)

    def _ids(self, points: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the pre-tokens, and the running count after each."""
        ends = np.append(starts[1:], len(points))
        h = spans_hash(points.astype(np.uint64) + np.uint64(1), starts, ends)
        slot = (h >> np.uint64(64 - 21)).astype(np.int64) & (self.slots - 1)
        late = np.flatnonzero(self.keys[slot] != h)
        count, source = self.count[slot].astype(np.int64), slot * self.WIDTH
        ids = self.ids
        if len(late):
            new, first, back = np.unique(h[late], return_index=True, return_inverse=True)
            at = late[first]
            n_new, flat = self._asked([points[a:b].tobytes().decode("utf-32-le") for a, b in zip(starts[at].tolist(), ends[at].tolist(), strict=True)])
            begin = np.cumsum(n_new) - n_new
            base = self.slots * self.WIDTH
            count[late], source[late] = n_new[back], base + begin[back]
            if len(flat) <= self.TAIL:
                ids[base : base + len(flat)] = flat
            else:
                ids = np.concatenate([ids[:base], flat])
        total = np.cumsum(count)
        out = ids[np.repeat(source - total + count, count) + np.arange(total[-1])]
        if len(late):
            # One new piece to a slot, if it fits; what was there goes.
            fit = np.flatnonzero(n_new <= self.WIDTH)
            s, one = np.unique(slot[at[fit]], return_index=True)
            fit = fit[one]
            self.keys[s], self.count[s] = new[fit], n_new[fit]
            for j in range(self.WIDTH):
                more = n_new[fit] > j
                self.ids[s[more] * self.WIDTH + j] = flat[begin[fit[more]] + j]
        return out, total


@lru_cache(4)
def encoder(library: str, path: str) -> Encoder:
    return Encoder(library, path)


CLEARED.append(encoder.cache_clear)


def code_points(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Code points of a string column (null: empty), and where each row starts."""
    texts = [x or "" for x in column.to_pylist()]
    offsets = np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))]).astype(np.int64)
    return np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32), offsets
