"""Encoding of whole texts piece by piece, with a bounded cache of pieces.

A text is cut only where no tokenizer of the kind at hand can look across the cut, so that the ids of
the pieces, put together, are those of the text.
"""

from __future__ import annotations

import hashlib
import json
import re
import zlib

#: Entries of a worker's caches of words and of pieces; a cache is emptied when full, so memory stays bounded.
WORDS, PIECES = 800_000, 600_000
#: The same of the encoder by ranks, whose entries hold their texts.
RANKED = 350_000
#: Characters up to which a word's ranks are scanned for the least.
SHORT = 128
#: Plain pieces: letters of Basic Latin and Latin-1, which no tokenizer here composes or splits, then signs.
PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([.,;:!?|]*)").fullmatch
_OPEN: dict[tuple, object] = {}


def packed(path: str) -> bytes:
    """The tokenizer file for use in tasks: executors need not have the file at this path."""
    with open(path, "rb") as f:
        return zlib.compress(f.read(), 6)


def opened(kind, spec: bytes):
    """One encoder per worker process."""
    key = kind, hashlib.sha256(spec).digest()
    if key not in _OPEN:
        _OPEN.clear()
        _OPEN[key] = kind(zlib.decompress(spec).decode())
    return _OPEN[key]


class LibraryPieces:
    """Byte-level BPE by the tokenizers library, called on distinct pieces only.

    Its pattern takes at most one space before a word, number or run of signs. So between two characters
    that aren't white space, a single space always starts a token: cuts are made right before such spaces.
    """

    def __init__(self, spec: str):
        import numpy as np
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(spec)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.separator = max((t for t in json.loads(spec)["added_tokens"] if t["special"]), key=lambda t: t["id"])
        #: Letters are kept for the piece with a space before them, signs and all else (with its space) as they are.
        self.words: dict[str, bytes] = {}
        self.pieces: dict[str, bytes] = {}
        self.np = np
        names = self.tokenizer.get_vocab()
        self.length = np.zeros(max(names.values()) + 1, np.int64)
        for name, i in names.items():
            self.length[i] = len(name)

    def _bytes(self, texts: list[str]) -> list[bytes]:
        """Ids of each text. A special token is cut out before all else, so texts joined by one are encoded apart."""
        if len(texts) == 1 or any(self.separator["content"] in x for x in texts):
            return [self.np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        ids = self.np.array(self.tokenizer.encode_batch_fast([self.separator["content"].join(texts)], add_special_tokens=False)[0].ids, "<u4")
        cuts = self.np.flatnonzero(ids == self.separator["id"]).tolist()
        raw = ids.tobytes()
        return [raw[4 * a : 4 * b] for a, b in zip([0, *[c + 1 for c in cuts]], [*cuts, len(ids)])]

    def _spaced(self, words: list[str]) -> list[bytes]:
        """Ids of each word of letters with a space before it. A run of such words is encoded at once: a space starts
        a token, and a token has as many bytes as its byte-level name has characters, so the ids part at the words' ends."""
        out: list[bytes] = []
        for at in range(0, len(words), 512):
            some = words[at : at + 512]
            ids = self.np.array(self.tokenizer.encode_batch_fast(["".join([" " + w for w in some])], add_special_tokens=False)[0].ids, "<u4")
            ends = self.np.cumsum(self.length[ids])
            cuts = (self.np.searchsorted(ends, self.np.cumsum([len(w.encode()) + 1 for w in some])) + 1).tolist()
            raw = ids.tobytes()
            out += [raw[4 * a : 4 * b] for a, b in zip([0, *cuts], cuts)]
        return out

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return self.encode_all([text])[0]

    def _learn(self, seen: set[str]) -> None:
        """Put the ids of all pieces of `seen` that stand after a space and have no white space at their ends into the cache."""
        pieces, words = self.pieces, self.words
        odd = seen.difference(pieces)
        if len(pieces) + len(odd) > PIECES:
            pieces.clear()
            odd = seen
        if len(words) > WORDS:
            words.clear()
        plain = {x: m.groups() for x in odd if (m := PLAIN(x))}
        words[""] = b""
        letters = list({w for w, _ in plain.values() if w not in words})
        words.update(zip(letters, self._spaced(letters)))
        new = [" " + x for x in odd if x not in plain] + list({s for _, s in plain.values() if s not in words})
        if new:
            words.update(zip(new, self._bytes(new)))
        pieces.update((x, words[m[0]] + words[m[1]]) for x, m in plain.items())
        for x in odd - plain.keys():
            pieces[x] = words.pop(" " + x)

    def encode_column(self, col):
        """Ids of all texts of an Arrow column in one array, and each text's offset (texts + 1 entries); null is empty.

        The column is cut at spaces and dictionary-encoded in Arrow, so that Python sees distinct pieces only.
        """
        import pyarrow.compute as pc

        np = self.np
        lists = pc.split_pattern(pc.fill_null(col, ""), " ")
        count = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
        coded = lists.flatten().dictionary_encode()
        names, place = coded.dictionary.to_pylist(), coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        begin = np.cumsum(count) - count
        firsts = [names[i] for i in place[begin].tolist()]
        white = np.array([not x or x[0].isspace() or x[-1].isspace() for x in names], bool)
        seen = {x for x, w in zip(names, white.tolist()) if not w}
        self._learn(seen)
        table = [b"" if w else self.pieces[x] for x, w in zip(names, white.tolist())]
        for x in [x for x in seen if len(x) >= 64]:
            self.pieces.pop(x, None)
        # A text's first piece has no space before it; a text with white space beside a space is one entry as a whole.
        odd = white[place]
        odd[begin] = [bool(n > 1) and not x or x[:1].isspace() or x[-1:].isspace() for x, n in zip(firsts, count.tolist())]
        whole = np.flatnonzero(np.add.reduceat(odd, begin)) if len(begin) else begin
        table += self._bytes(firsts) if firsts else []
        place[begin] = len(names) + np.arange(len(firsts))
        keep = np.ones(len(place), bool)
        for i in whole.tolist():
            a, n = int(begin[i]), int(count[i])
            rest = [names[k] for k in place[a + 1 : a + n].tolist()]
            place[a] = len(table)
            table.append(self._with_white_space(firsts[i], rest))
            keep[a + 1 : a + n] = False
        held = np.array([len(x) // 4 for x in table], np.int64)
        flat, at = np.frombuffer(b"".join(table), "<u4"), np.cumsum(held) - held
        text = np.repeat(np.arange(len(count)), count)[keep]
        place = place[keep]
        size = held[place]
        ends = np.cumsum(size)
        ids = flat[np.repeat(at[place] - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)]
        return ids, np.concatenate([[0], np.cumsum(np.bincount(text, size, len(count)).astype(np.int64))])

    def encode_all(self, texts: list[str]) -> list[bytes]:
        import pyarrow as pa

        if not texts:
            return []
        ids, off = self.encode_column(pa.array(texts, pa.string()))
        return [ids[a:b].tobytes() for a, b in zip(off[:-1].tolist(), off[1:].tolist())]

    def _with_white_space(self, first: str, rest: list[str]) -> bytes:
        """Cut only where neither side of the space is white space."""
        glued = [first]
        for x in rest:
            last = glued[-1]
            if x and last and not x[0].isspace() and not last[-1].isspace():
                glued.append(" " + x)
            else:
                glued[-1] += " " + x
        return b"".join(self._bytes(glued))


class RankArrayPieces:
    """BPE by a contiguous rank array, with the file's own normalizer and pre-tokenizer.

    A short word is held as its part boundaries and, beside them, the rank of merging each part with the next.
    The least rank is found by scanning; its inner boundary is deleted and the two ranks next to it are refreshed.
    The normalizer turns white space into spaces and the pre-tokenizer drops them, so any space or newline is a cut.
    """

    def __init__(self, spec: str):
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_str(spec)
        self.normalizer, self.pre = tokenizer.normalizer, tokenizer.pre_tokenizer
        file = json.loads(spec)
        model = file["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.ranks = {tuple(m.split(" ") if isinstance(m, str) else m): r for r, m in enumerate(model["merges"])}
        self.special = {t["content"]: t["id"] for t in file["added_tokens"]}
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.token = {i: t for t, i in (self.vocab | self.special).items()}
        self.byte = {i: self.pre.pre_tokenize_str(chr(i))[0][0] for i in range(33, 127)} | self._bytes_above()
        self.words: dict[str, tuple] = {}
        self.cache: dict[str, tuple] = {}

    @staticmethod
    def _bytes_above() -> dict[int, str]:
        """The byte-level alphabet above 127: printable Latin-1 stands for itself, the others follow from code point 256 on."""
        shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
        hidden = [b for b in range(256) if b not in shown]
        return {b: chr(b) if b in shown else chr(256 + hidden.index(b)) for b in range(128, 256)}

    def word(self, word: str) -> list[int]:
        ranks = self.ranks.get
        none = len(self.ranks)
        parts = list(word)
        parts[-1] += self.suffix
        if len(parts) > SHORT:
            return self._long(parts)
        adjacent = [ranks(p, none) for p in zip(parts, parts[1:])]
        while adjacent:
            least = min(adjacent)
            if least == none:
                break
            i = adjacent.index(least)
            parts[i] += parts.pop(i + 1)  # the boundary between the two goes
            del adjacent[i]
            if i < len(adjacent):
                adjacent[i] = ranks((parts[i], parts[i + 1]), none)
            if i:
                adjacent[i - 1] = ranks((parts[i - 1], parts[i]), none)
        return [self.vocab[p] for p in parts if p in self.vocab]

    def _long(self, parts: list[str]) -> list[int]:
        """The same merges for a long run without a cut, where scanning would take quadratic time: least rank, then leftmost, by a heap."""
        import heapq

        ranks, n = self.ranks.get, len(parts)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, parts[i], parts[i + 1]) for i in range(n - 1) if (r := ranks((parts[i], parts[i + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            j = after[i]
            if parts[i] != a or j >= n or parts[j] != b:
                continue  # one of the two has been merged since
            parts[i], parts[j] = a + b, ""
            after[i] = j = after[j]
            if j < n:
                before[j] = i
            for k in (before[i], i):
                if k >= 0 and after[k] < n and (r := ranks((parts[k], parts[after[k]]))) is not None:
                    heapq.heappush(heap, (r, k, parts[k], parts[after[k]]))
        return [self.vocab[p] for p in parts if p in self.vocab]

    def _entry(self, ids: list[int]) -> tuple[int, str, str]:
        return len(ids), " ".join(map(str, ids)), " ".join([self.token[i] for i in ids])

    def _word(self, word: str) -> tuple[int, str, str]:
        e = self.words.get(word)
        if e is None:
            e = self._entry(self.word(word if word.isascii() else "".join([self.byte[b] for b in word.encode()])))
            if len(self.words) >= RANKED:
                self.words.clear()
            if len(word) < 64:
                self.words[word] = e
        return e

    def piece(self, piece: str) -> tuple[int, str, str]:
        if m := PLAIN(piece):
            word = self._word(m[1].lower())
            if not m[2]:
                return word
            return tuple(a + b if isinstance(a, int) else f"{a} {b}" for a, b in zip(word, self._word(m[2])))
        out: list[int] = []
        for run in self.cut.split(piece) if self.cut else [piece]:
            if run in self.special:
                out.append(self.special[run])
            elif run:
                for word, _ in self.pre.pre_tokenize_str(self.normalizer.normalize_str(run)):
                    if word:
                        out += self.word(word)
        return self._entry(out)

    def entries_all(self, texts: list[str]) -> list[list[tuple[int, str, str]]]:
        """For each text and piece: number of ids, the ids as text, their tokens as text; both joined by spaces."""
        cache = self.cache
        cut = [[p for p in t.replace("\n", " ").split(" ") if p] for t in texts]
        seen = set().union(*cut)
        odd = seen.difference(cache)
        if len(cache) + len(odd) > RANKED:
            cache.clear()
            odd = seen
        cache.update((p, self.piece(p)) for p in odd)
        out = [[e for e in map(cache.__getitem__, c) if e[0]] for c in cut]
        for p in [p for p in odd if len(p) >= 64]:
            del cache[p]
        return out

    def entries(self, text: str) -> list[tuple[int, str, str]]:
        return self.entries_all([text])[0]

    def encode(self, text: str) -> list[int]:
        return [int(i) for e in self.entries(text) for i in e[1].split(" ")]

    def decode(self, ids: list[int]) -> str:
        """Without a decoder in the file, tokens are joined by spaces; unknown ids are left out."""
        return " ".join([self.token[i] for i in ids if i in self.token])
