"""BPE encoding by speculation and verification, and decoding.

`Bpe` reads a tokenizer file (JSON with a byte-level BPE model). A piece of text is encoded in three steps: greedy longest match proposes
tokens; each adjacent pair of proposals is checked for compatibility, for all pairs of a batch at once; pieces with an
incompatible pair go through exact merging, which is vectorised over pieces too.

Two tokens are compatible when merging never crosses the border between them. Only the tokens that touch the border matter: on the
left the chain of right halves from the last symbol up to the whole token, on the right the chain of left halves. The check
walks both chains in merge order and fails when the pair that touches would merge first. Pairwise compatibility of whole
tokens that each encode to themselves is enough for the sequence to be the BPE encoding.

`WordBpe` and `ByteBpe` split whole texts as the two file kinds do (words with ends and lower case; bytes with spaces kept). Splitting is
vectorised over the characters of a block of texts, pieces are told apart by 64-bit hashes, and the ids of known pieces are gathered
from flat arrays, so that only pieces that a worker has not seen are spelled out in Python. Texts with special tokens or odd control
characters go to the tokenizers library itself.
"""

from __future__ import annotations

import json
import re
import sys
import unicodedata
from functools import cached_property

import numpy as np
from tokenizers import Tokenizer

from retro.llm.vector_text import mix64, span_sums

_NEVER = np.int64(1 << 40)
_TOP = np.int64((1 << 31) - 1)  # stands for _NEVER where ranks are kept in 32 bits


def byte_letters() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies: printable Latin-1 stands for itself, the rest from U+0100 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(own)]
    table = {b: chr(b) for b in own} | {b: chr(256 + k) for k, b in enumerate(rest)}
    return [table[b] for b in range(256)]


class Bpe:
    #: Pieces that a worker remembers; beyond them it starts anew. An entry is 20 bytes and 4 for each id; inserting copies them for a moment.
    remember = 250_000
    #: Greedy matches of short ends that are remembered (Python objects, some 200 bytes each).
    tails = 100_000
    #: Whether tokens are proposed and verified first, or all pieces merged exactly at once. The ids are the same.
    speculate = True

    def __init__(self, source: str):
        spec = json.loads(source)
        model = spec["model"]
        self._source, self._library = source, None
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.suffix = model["end_of_word_suffix"] or ""
        vocab: dict[str, int] = model["vocab"]
        self.size = max(*vocab.values(), *(t["id"] for t in spec["added_tokens"])) + 1
        self.token = [""] * self.size
        for text, k in vocab.items():
            self.token[k] = text
        for t in spec["added_tokens"]:
            self.token[t["id"]] = t["content"]
        merges = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        left, right = (np.array([vocab[m[k]] for m in merges], dtype=np.int64) for k in (0, 1))
        made = np.array([vocab[a + b] for a, b in merges], dtype=np.int64)
        key = left * self.size + right
        order = np.argsort(key, kind="stable")
        self._key, self._rank, self._made = key[order], order.astype(np.int64), made[order]
        slot = self._slot(self._key)
        self._table = np.full(1 << 18, -1)
        self._table[slot] = np.arange(len(key))
        self._shared = np.zeros(1 << 18, dtype=bool)
        self._shared[slot[self._table[slot] != np.arange(len(key))]] = True
        self.letters = byte_letters()
        self._ascii = {b: self.letters[b] for b in range(128)}
        n = len(self.suffix)
        self._inner = {t: k for t, k in vocab.items() if not n or not t.endswith(self.suffix)}
        self._last = {t[:-n]: k for t, k in vocab.items() if t.endswith(self.suffix)} if n else vocab
        self._longest = max(map(len, vocab))
        self._reach: dict[str, int] = {}
        for t in self._inner:
            if len(t) > self._reach.get(t[:3], 2):
                self._reach[t[:3]] = len(t)
        self._byte_id = np.array([self._inner.get(c, 0) for c in self.letters])
        self._end_id = np.array([self._last.get(c, 0) for c in self.letters])
        self._tails: dict[str, tuple[int, ...]] = {}

    @property
    def library(self) -> Tokenizer:
        """The tokenizers library's own coder, made when a text first needs it."""
        if self._library is None:
            self._library = Tokenizer.from_str(self._source)
            self._library.no_truncation()
            self._library.no_padding()
        return self._library

    @cached_property
    def _borders(self) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
        """Whether each token encodes to itself and in one way; and for each token its chains of halves at either border, bottom
        up, with the rank of the merge that ends each link. Made when pairs are first checked."""
        made = np.empty(len(self._key), dtype=np.int64)
        made[self._rank] = self._made
        times = np.bincount(made, minlength=self.size)
        half = {0: np.full(self.size, -1), 1: np.full(self.size, -1)}
        half[0][self._made], half[1][self._made] = self._key // self.size, self._key % self.size
        rank = np.full(self.size, _NEVER)
        rank[made] = np.arange(len(made))
        spelled = [(t, k, False) for t, k in self._inner.items()] + [(t, k, True) for t, k in self._last.items() if self.suffix]
        symbols = [(self._symbols(t, ended), k) for t, k, ended in spelled]
        known = [(x, k) for x, k in symbols if x is not None]
        got, size = self.merged(np.fromiter((c for x, _ in known for c in x), np.int64), np.array([len(x) for x, _ in known]))
        one = size == 1
        whole = got[np.cumsum(size)[one] - 1]
        sound = np.zeros(self.size, dtype=bool)
        sound[whole[whole == np.array([k for _, k in known])[one]]] = True
        sound &= times <= 1
        chain = []
        for side in (1, 0):
            links = [np.arange(self.size)]
            while (half[side][links[-1]] >= 0).any():
                down = half[side][links[-1]]
                links.append(np.where(down >= 0, down, links[-1]))
            link = np.stack(links[::-1], axis=1).astype(np.int32)
            # the rank of the merge that turns a link into the next; repeats at the bottom are passed at once
            ends = np.concatenate([np.where(link[:, 1:] != link[:, :-1], rank[link[:, 1:]], -1), np.full((self.size, 1), _NEVER)], axis=1)
            ends = np.minimum(ends, _TOP).astype(np.int32)
            chain.append((link, ends))
        return sound, chain

    def _symbols(self, letters: str, ended: bool) -> list[int] | None:
        try:
            out = [self._inner[c] for c in letters]
            if self.suffix and ended:
                out[-1] = self._last[letters[-1]]
            return out
        except (KeyError, IndexError):
            return None

    @staticmethod
    def _slot(key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(46)).astype(np.int64)

    def _look_up(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (or never) and place of the merge of each pair, from a hash table; keys that share a slot are searched for."""
        key = a * self.size + b
        slot = self._slot(key)
        at = np.maximum(self._table[slot], 0)
        good = self._key[at] == key
        other = np.flatnonzero(~good & self._shared[slot])
        if len(other):
            at[other] = np.minimum(np.searchsorted(self._key, key[other]), len(self._key) - 1)
            good[other] = self._key[at[other]] == key[other]
        return np.where(good, self._rank[at], _NEVER), at

    def compatible(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        (up_a, end_a), (up_b, end_b) = self._borders[1]
        good, i, j = np.ones(len(a), dtype=bool), np.zeros(len(a), np.int64), np.zeros(len(a), np.int64)
        live = np.arange(len(a))
        while len(live):
            p, q = a[live], b[live]
            x, y, na, nb = up_a[p, i[live]], up_b[q, j[live]], end_a[p, i[live]], end_b[q, j[live]]
            c = np.minimum(self._look_up(x.astype(np.int64), y.astype(np.int64))[0], _TOP)
            crossed = (c < na) & (c <= nb)
            good[live[crossed]] = False
            step = na <= nb
            i[live] += step
            j[live] += ~step
            live = live[~crossed & ((na < _TOP) | (nb < _TOP))]
        return good

    def _symbols_of(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of pieces (texts, not byte letters) one after the other, and the number of each."""
        size = np.array([len(p) if p.isascii() else len(p.encode()) for p in pieces], dtype=np.int64)
        data = np.frombuffer("".join(pieces).encode(), np.uint8)
        ids = self._byte_id[data]
        if self.suffix:
            last = np.cumsum(size) - 1
            ids[last] = self._end_id[data[last]]
        return ids, size

    def merged(self, ids: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Exact merging: in each piece the lowest ranked pair merges everywhere, from the left, until none is left.
        ids: symbols of the pieces one after the other; gives the tokens likewise."""
        pieces = len(size)
        owner = np.repeat(np.arange(pieces), size)
        done_ids, done_owner = [], []
        while len(ids):
            rank = np.full(len(ids), _NEVER)
            inside = np.flatnonzero(owner[1:] == owner[:-1])
            rank[inside], at = self._look_up(ids[inside], ids[inside + 1])
            place = np.zeros(len(ids), np.int64)
            place[inside] = at
            start = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1])))
            best = np.minimum.reduceat(rank, start)
            least = np.repeat(best, np.diff(np.concatenate((start, [len(ids)]))))
            done = least == _NEVER
            done_ids.append(ids[done])
            done_owner.append(owner[done])
            hit = (rank == least) & ~done
            again = np.flatnonzero(hit[1:] & hit[:-1])
            if len(again):
                # of overlapping hits every second one merges, from the left
                first = hit & ~np.concatenate(([False], hit[:-1]))
                hit &= (np.arange(len(ids)) - np.maximum.accumulate(np.where(first, np.arange(len(ids)), 0))) % 2 == 0
            ids = np.where(hit, self._made[place], ids)
            keep = ~done
            keep[1:] &= ~hit[:-1]
            ids, owner = ids[keep], owner[keep]
        if not done_ids:
            return np.zeros(0, np.int64), np.zeros(pieces, np.int64)
        owner = np.concatenate(done_owner)
        order = np.argsort(owner, kind="stable")
        return np.concatenate(done_ids)[order], np.bincount(owner, minlength=pieces)

    def _proposed(self, piece: str) -> tuple[int, ...] | None:
        """Greedy longest match. What follows the first match depends on the rest of the piece alone and is remembered."""
        memory = self._tails
        out = memory.get(piece)
        if out is None:
            n, inner = len(piece), self._inner
            k = self._last.get(piece)
            if k is not None:
                out = (k,)
            else:
                for end in range(min(n - 1, self._reach.get(piece[:3], 2)), 0, -1):
                    k = inner.get(piece[:end])
                    if k is not None:
                        rest = self._proposed(piece[end:]) if n < 200 else self._walked(piece[end:])
                        out = (k, *rest) if rest is not None else None
                        break
            if n <= 8 and out is not None and len(memory) < self.tails:
                memory[piece] = out
        return out

    def _walked(self, piece: str) -> tuple[int, ...] | None:
        """The same without recursion, for long pieces."""
        out, at, n = [], 0, len(piece)
        while at < n:
            for end in range(min(n, at + self._longest), at, -1):
                k = (self._inner if end < n else self._last).get(piece[at:end])
                if k is not None:
                    out.append(k)
                    at = end
                    break
            else:
                return None
        return tuple(out)

    def encode_pieces(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Tokens of the pieces one after the other, and the number of each."""
        if not self.speculate:
            return self.merged(*self._symbols_of(pieces))
        proposed = [self._proposed(self.spell(p)) for p in pieces]
        size = np.array([len(p) if p else 0 for p in proposed], dtype=np.int64)
        flat = np.fromiter((k for p in proposed if p for k in p), np.int64, int(size.sum()))
        owner = np.repeat(np.arange(len(pieces)), size)
        bad = size == 0
        bad[owner[~self._borders[0][flat]]] = True
        at = np.flatnonzero(owner[1:] == owner[:-1])
        if len(at):
            key, back = np.unique(flat[at] * self.size + flat[at + 1], return_inverse=True)
            bad[owner[at[~self.compatible(key // self.size, key % self.size)[back]]]] = True
        failed = np.flatnonzero(bad)
        if len(failed):
            ids, more = self.merged(*self._symbols_of([pieces[k] for k in failed.tolist()]))
            good = ~bad[owner]
            owner = np.concatenate([owner[good], np.repeat(failed, more)])
            flat = np.concatenate([flat[good], ids])[np.argsort(owner, kind="stable")]
            size[failed] = more
        return flat, size

    # ---- whole texts -----------------------------------------------------------------------------------------------

    def spell(self, piece: str) -> str:
        return piece.translate(self._ascii) if piece.isascii() else "".join([self.letters[b] for b in piece.encode()])

    def plain(self, text: str) -> bool:
        return _ODD.search(text) is None and not any(s in text for s in self.special)

    def by_library(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def prepared(self, text: str) -> str:
        return text

    def starts(self, chars: np.ndarray, kinds: np.ndarray, border: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(starts, ends) of pieces. border: first characters of texts; left: characters from each on to its text's end."""
        raise NotImplementedError

    def _forget(self) -> None:
        self._hash, self._at, self._size = np.zeros(0, np.uint64), np.zeros(0, np.int32), np.zeros(0, np.int32)
        self._hits = np.zeros(0, np.uint32)
        self._flat, self._used = np.zeros(1 << 16, "<u4"), 0

    def _thin(self) -> None:
        """Forgets the pieces that one block alone has used, or all when the others are too many as well."""
        kept = np.flatnonzero(self._hits > 1)
        size = self._size[kept]
        if len(kept) > self.remember // 2 or int(size.sum()) > 8 * self.remember:
            return self._forget()
        ends = np.cumsum(size)
        flat = self._flat[np.repeat(self._at[kept] - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)]
        self._hash, self._size, self._hits, self._at = self._hash[kept], size, np.ones(len(kept), np.uint32), (ends - size).astype(np.int32)
        self._flat, self._used = np.concatenate([flat, np.zeros(1 << 16, "<u4")]), len(flat)

    def _learn(self, codes: np.ndarray, pieces: list[str]) -> None:
        ids, size = self.encode_pieces(pieces)
        if self._used + len(ids) > len(self._flat):
            self._flat = np.concatenate([self._flat[: self._used], np.zeros(len(ids) + self._used // 2, "<u4")])
        self._flat[self._used : self._used + len(ids)] = ids
        where = np.searchsorted(self._hash, codes)
        at = self._used + np.concatenate(([0], np.cumsum(size)[:-1]))
        self._hash, self._at, self._size, self._hits = (np.insert(x, where, y) for x, y in ((self._hash, codes), (self._at, at), (self._size, size), (self._hits, 0)))
        self._used += len(ids)

    def encode(self, texts: list[str]) -> list[bytes]:
        plain = [self.plain(t) for t in texts]
        ready = [self.prepared(t) if ok else "" for t, ok in zip(texts, plain, strict=True)]
        joined = "".join(ready)
        offsets = np.concatenate(([0], np.cumsum([len(t) for t in ready])))
        chars = np.frombuffer(joined.encode("utf-32-le"), "<u4")
        if not len(chars):
            return [b"" if ok else self.by_library(t) for t, ok in zip(texts, plain, strict=True)]
        border = np.zeros(len(chars) + 1, dtype=bool)
        border[offsets] = True
        left = np.repeat(offsets[1:], np.diff(offsets)) - np.arange(len(chars))
        start, end = self.starts(chars, _KINDS[chars], border[:-1], left)
        codes, first, back = np.unique(span_sums(_CODES[chars], start, end), return_index=True, return_inverse=True)
        if len(self._hash) + len(codes) > self.remember or self._used > 16 * self.remember:
            self._thin()
        at = np.minimum(np.searchsorted(self._hash, codes), max(0, len(self._hash) - 1))
        new = self._hash[at] != codes if len(self._hash) else np.ones(len(codes), dtype=bool)
        if new.any():
            k = first[new]
            self._learn(codes[new], [joined[a:b] for a, b in zip(start[k].tolist(), end[k].tolist(), strict=True)])
            at = np.searchsorted(self._hash, codes)
        self._hits[at] += 1
        at = at[back]
        size = self._size[at].astype(np.int64)
        ends = np.cumsum(size)
        ids = self._flat[np.repeat(self._at[at] - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)].tobytes()
        cut = 4 * np.concatenate(([0], ends))[np.searchsorted(start, offsets)]
        return [ids[a:b] if ok else self.by_library(t) for t, ok, a, b in zip(texts, plain, cut[:-1].tolist(), cut[1:].tolist(), strict=True)]

    def decode(self, ids: np.ndarray) -> str:
        """As the library decodes without a decoder: tokens with a space between."""
        token = self.token
        return " ".join([token[k] for k in ids.tolist()])


_ODD = re.compile("[\x00\x1c-\x1f]")
_OTHER, _SPACE, _LETTER, _NUMBER = range(4)


def _kinds() -> np.ndarray:
    """The kind of every character: Unicode white space, letters, numbers, the rest."""
    group = {"L": _LETTER, "N": _NUMBER}
    out = np.fromiter((group.get(unicodedata.category(chr(c))[0], _OTHER) for c in range(sys.maxunicode + 1)), np.uint8, sys.maxunicode + 1)
    out[[9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]] = _SPACE
    return out


_KINDS = _kinds()
_CODES = mix64(np.arange(1, sys.maxunicode + 2, dtype=np.uint64))


def _contractions(chars: np.ndarray, at: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of apostrophes at `at`, those that begin one of the seven English endings, and the ends of these."""
    get = lambda k: np.where(left[at] > k, chars[np.minimum(at + k, len(chars) - 1)], 0)
    one, two = get(1), get(2)
    short = np.isin(one, [ord(c) for c in "stmd"])
    long = (one == ord("r")) & (two == ord("e")) | (one == ord("v")) & (two == ord("e")) | (one == ord("l")) & (two == ord("l"))
    size = np.where(short, 2, np.where(long, 3, 0))
    return at[size > 0], (at + size)[size > 0]


def _split_endings(first: np.ndarray, chars: np.ndarray, kinds: np.ndarray, left: np.ndarray, spaced: bool) -> None:
    """Marks the piece starts that contractions add and clears those inside them. spaced: a space before joins the apostrophe to it."""
    at = np.flatnonzero((chars == 39) & first)
    if spaced and len(at):
        at = at[~((at > 0) & (chars[np.maximum(at - 1, 0)] == 32) & (left[np.maximum(at - 1, 0)] > 1))]
    if len(at):
        at, end = _contractions(chars, at, left)
        first[at + 1] = False
        inside = left[at] > end - at
        first[end[inside]] = True


class WordBpe(Bpe):
    """Words with ends: NFC, lower case, white space dropped, digits one by one."""

    def __init__(self, source: str):
        super().__init__(source)
        self._forget()

    def prepared(self, text: str) -> str:
        return text.lower() if text.isascii() else unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()

    def starts(self, chars, kinds, border, left):
        first = border.copy()
        first[1:] |= kinds[1:] != kinds[:-1]
        first |= kinds == _NUMBER
        _split_endings(first, chars, kinds, left, spaced=False)
        start = np.flatnonzero(first)
        end = np.append(start[1:], len(chars))
        kept = kinds[start] != _SPACE
        return start[kept], end[kept]


class ByteBpe(Bpe):
    """Bytes with spaces kept: a single space joins what follows it."""

    speculate = False

    def __init__(self, source: str):
        super().__init__(source)
        self._forget()

    def starts(self, chars, kinds, border, left):
        first = border.copy()
        first[1:] |= kinds[1:] != kinds[:-1]
        # last characters of white space that text follows: a space joins the next piece, another one stands alone
        last = np.flatnonzero((kinds[:-1] == _SPACE) & (kinds[1:] != _SPACE) & (left[:-1] > 1))
        _split_endings(first, chars, kinds, left, spaced=True)
        first[last] = True
        first[last[chars[last] == 32] + 1] = False
        start = np.flatnonzero(first)
        return start, np.append(start[1:], len(chars))


_loaded: dict[tuple[str, int], Bpe] = {}


def loaded(kind: type[Bpe], source: str) -> Bpe:
    """One coder a worker process for each file."""
    key = (kind.__name__, hash(source))
    if key not in _loaded:
        _loaded[key] = kind(source)
    return _loaded[key]


def runs(texts: list[str], limit: int = 1 << 19):
    """Slices of about `limit` characters (one longer text makes a slice)."""
    first, size = 0, 0
    for k, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield first, k
            first, size = k, 0
        size += len(t)
    if first < len(texts):
        yield first, len(texts)
