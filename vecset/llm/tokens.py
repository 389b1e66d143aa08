"""Byte-level BPE in bulk: a text is cut where no match of the split pattern can span, each distinct chunk is encoded once.

Every whitespace that the pattern joins to other text is one space before a non-space. So a text may be cut before each space
that stands between two non-spaces, and the ids of the text are the ids of its chunks in order. A chunk comes back again and
again; its ids are kept in a table of bounded size.
"""

from __future__ import annotations

import base64
import functools
import os

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

from .common import kept, ranges  # noqa: E402


@functools.cache
def byte_chars() -> list[str]:
    """The character that stands for each byte in byte-level vocabularies: printable ones for themselves, the rest from 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


def load_json(path: str):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.encode_special_tokens = True
    return t


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def from_ranks(ranks: dict[bytes, int], pattern: str):
    """A tokenizer of the tokenizers library with the merges that a rank table implies, which encodes each match of pattern by itself.
    A match that is a token is taken whole, as a merge by ranks does."""
    from tokenizers import Regex, Tokenizer, models, pre_tokenizers

    char = byte_chars()
    name = lambda token: "".join(char[b] for b in token)
    merges = []
    for token, _ in sorted(ranks.items(), key=lambda x: x[1]):
        cuts = [(token[:i], token[i:]) for i in range(1, len(token)) if token[:i] in ranks and token[i:] in ranks]
        cuts = [c for c in cuts if max(ranks[c[0]], ranks[c[1]]) < ranks[token]] or cuts
        merges += [(name(a), name(b)) for a, b in cuts]
    t = Tokenizer(models.BPE({name(k): v for k, v in ranks.items()}, merges, ignore_merges=True))
    t.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.Split(Regex(pattern), "isolated"), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
    return t


#: Punctuation that ends a word's last match: no alternative of the pattern spans a letter and one of these.
MARKS = ".,;:!?%$#&*)]}>\"-"


class _Slots(dict):
    """Piece after a space -> slot; -1 if the cuts around it depend on its neighbours."""

    def __init__(self, owner):
        self.owner = owner

    def __missing__(self, piece: str) -> int:
        if piece.isalpha():
            slot = self.owner.new(" " + piece, True)
        else:
            word = piece.rstrip(MARKS)
            if word.isalpha():
                slot = self.owner.join([self[word], self.owner.slot(piece[len(word) :])])
            else:
                slot = -1 if not piece or piece[0].isspace() or piece[-1].isspace() else self.owner.compose(piece)
        self[piece] = slot
        return slot


def may_cut(tokenizer) -> bool:
    """Whether the tokenizer's pattern ends a match at every place where an Encoder cuts: before a space or a line end between others,
    and between letters and the marks after them."""
    for text, cuts in [("ab cd", {2}), ("ab\ncd", {2}), (".) ab", {2}), *((f"ab{m}", {2}) for m in MARKS)]:
        starts = {a for _, (a, _) in tokenizer.pre_tokenizer.pre_tokenize_str(text)} if tokenizer.pre_tokenizer else set()
        if not cuts <= starts:
            return False
    return True


class Encoder:
    """encode(texts) -> (ids of all texts in a row, ids of each text). Where the tokenizer's pattern doesn't allow the cuts, texts go whole.

    most: chunks kept; beyond it those stay that were used twice since they came.
    """

    def __init__(self, tokenizer, most: int = 600_000):
        self.tokenizer, self.most, self.cuts = tokenizer, most, may_cut(tokenizer)
        vocab, byte = tokenizer.get_vocab(), set(byte_chars())
        self.width = np.zeros(max(vocab.values()) + 1, np.int64)
        for token, i in vocab.items():
            self.width[i] = len(token) if byte.issuperset(token) else len(token.encode())
        self.clear()

    def clear(self) -> None:
        self.tail, self.whole, self.n = _Slots(self), {}, 0
        self.glued, self.alone, self.joined = [], [], []
        self.flat, self.start, self.size, self.used = np.zeros(0, np.uint32), np.zeros(0, np.int32), np.zeros(0, np.int32), np.zeros(0, np.int32)

    def new(self, chunk: str, glue: bool) -> int:
        """glue: the chunk starts with one space or line end before a non-space, and ends with a non-space."""
        (self.glued if glue else self.alone).append((self.n, chunk))
        self.n += 1
        return self.n - 1

    def slot(self, chunk: str, glue: bool = False) -> int:
        found = self.whole.get(chunk)
        if found is None:
            found = self.whole[chunk] = self.new(chunk, glue)
        return found

    def join(self, parts: list[int]) -> int:
        self.joined.append((self.n, parts))
        self.n += 1
        return self.n - 1

    def compose(self, piece: str) -> int:
        """A single line end between non-spaces is a match of its own, and so is what follows a word's letters."""
        lines = piece.split("\n") if "\n" in piece else [piece]
        if len(lines) > 1 and all(x and not x[0].isspace() and not x[-1].isspace() for x in lines):
            parts = [self.tail[lines[0]]]
            for line in lines[1:]:
                word = line.rstrip(MARKS)
                if word and word[-1].isalpha() and len(word) < len(line):
                    parts += [self.slot("\n" + word, True), self.slot(line[len(word) :])]
                else:
                    parts.append(self.slot("\n" + line, True))
            return self.join(parts)
        word = piece.rstrip(MARKS)
        if word and word[-1].isalpha() and len(word) < len(piece):
            return self.join([self.tail[word], self.slot(piece[len(word) :])])
        return self.new(" " + piece, True)

    def prune(self) -> None:
        kept = np.flatnonzero(self.used >= 2)
        if len(kept) > self.most // 2:
            return self.clear()
        new = np.full(self.n, -2)
        new[kept] = np.arange(len(kept))
        to = new.tolist()
        tail = _Slots(self)
        tail.update((k, -1 if v < 0 else to[v]) for k, v in self.tail.items() if v >= 0 and to[v] >= 0)
        self.tail, self.whole, self.n = tail, {k: to[v] for k, v in self.whole.items() if to[v] >= 0}, len(kept)
        self.flat = self.flat[ranges(self.start[kept], self.size[kept])]
        self.size = self.size[kept]
        self.start, self.used = (np.cumsum(self.size) - self.size).astype(np.int32), np.zeros(len(kept), np.int32)

    def cut(self, text: str) -> np.ndarray:
        """Slots of the text's chunks."""
        if not text:
            return np.zeros(0, np.int64)
        head, *rest = text.split(" ")
        slots = np.fromiter(map(self.tail.__getitem__, rest), np.int64, len(rest))
        plain = bool(head) and not head[0].isspace() and not head[-1].isspace()
        odd = np.flatnonzero(slots < 0) + 1
        if plain and not len(odd):
            return np.concatenate(([self.slot(head)], slots))
        pieces = [head, *rest]
        free = np.ones(len(pieces) + 1, bool)
        for i in odd.tolist() if plain else [0, *odd.tolist()]:
            p = pieces[i]
            if i and (not p or p[0].isspace()):
                free[i] = False
            if not p or p[-1].isspace():
                free[i + 1] = False
        free[0] = free[-1] = True
        at = np.flatnonzero(free)
        out = np.concatenate(([-1], slots))[at[:-1]]
        for k in np.flatnonzero((np.diff(at) > 1) | (out < 0)).tolist():
            a, b = int(at[k]), int(at[k + 1])
            out[k] = self.slot((" " if a else "") + " ".join(pieces[a:b]))
        return out

    def learn(self) -> None:
        """Encodes the chunks that are new. Glued ones go in runs, as one text; their ids are told apart by their bytes."""
        if self.n == len(self.size):
            return
        old = len(self.size)
        start, size = np.zeros(self.n - old, np.int32), np.zeros(self.n - old, np.int32)
        flats, base = [self.flat], len(self.flat)

        def put(todo: list, ids: np.ndarray, sizes: np.ndarray) -> None:
            nonlocal base
            slots = np.fromiter((s for s, _ in todo), np.int64, len(todo)) - old
            size[slots], start[slots] = sizes, base + np.cumsum(sizes) - sizes
            flats.append(ids)
            base += len(ids)

        if self.glued:
            chunks = [c for _, c in self.glued]
            runs = ["".join(chunks[i : i + 64]) for i in range(0, len(chunks), 64)]
            got = [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(runs, add_special_tokens=False)]
            ids, ends = np.concatenate(got), np.cumsum(np.fromiter((len(c.encode()) for c in chunks), np.int64, len(chunks)))
            at = np.searchsorted(np.cumsum(self.width[ids]), ends) + 1
            put(self.glued, ids, np.diff(at, prepend=0))
        if self.alone:
            got = [e.ids for e in self.tokenizer.encode_batch([c for _, c in self.alone], add_special_tokens=False)]
            put(self.alone, np.fromiter((i for x in got for i in x), np.uint32), np.fromiter(map(len, got), np.int64, len(got)))
        self.start, self.size, self.flat = np.concatenate((self.start, start)), np.concatenate((self.size, size)), np.concatenate(flats)
        if self.joined:
            n = np.fromiter((len(p) for _, p in self.joined), np.int64, len(self.joined))
            slots, parts = np.fromiter((s for s, _ in self.joined), np.int64, len(n)), np.fromiter((x for _, p in self.joined for x in p), np.int64, int(n.sum()))
            nested = np.zeros(self.n, bool)
            nested[slots] = True
            deep = np.maximum.reduceat(nested[parts], np.cumsum(n) - n)  # made of other joined ones: after those
            for some in (~deep, deep):
                k, m = np.repeat(some, n), n[some]
                if len(m):
                    sizes = np.add.reduceat(self.size[parts[k]], np.cumsum(m) - m)
                    self.size[slots[some]], self.start[slots[some]] = sizes, len(self.flat) + np.cumsum(sizes) - sizes
                    self.flat = np.concatenate((self.flat, self.flat[ranges(self.start[parts[k]], self.size[parts[k]])]))
        self.used = np.concatenate((self.used, np.zeros(self.n - old, np.int32)))
        self.glued, self.alone, self.joined = [], [], []

    def encode(self, texts: list) -> tuple[np.ndarray, np.ndarray]:
        if not self.cuts:
            ids = [e.ids for e in self.tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)]
            return np.fromiter((i for x in ids for i in x), np.uint32), np.fromiter(map(len, ids), np.int64, len(ids))
        if self.n > self.most:
            self.prune()
        cuts = [self.cut(t or "") for t in texts]
        self.learn()
        slots = np.concatenate(cuts) if cuts else np.zeros(0, np.int64)
        self.used += np.bincount(slots, minlength=self.n).astype(np.int32)
        size = self.size[slots]
        ends = np.concatenate(([0], np.cumsum(size)))
        at = np.concatenate(([0], np.cumsum([len(c) for c in cuts]))).astype(np.int64)
        return self.flat[ranges(self.start[slots], size)], np.diff(ends[at])


def json_encoder(path: str) -> Encoder:
    """One for each worker process and file."""
    return kept(("json", path), lambda: Encoder(load_json(path)))


def rank_encoder(path: str, pattern: str) -> tuple[Encoder, "ByteTable"]:
    """One for each worker process and file."""

    def make():
        tokenizer = from_ranks(read_ranks(path), pattern)
        return Encoder(tokenizer), ByteTable(tokenizer.get_vocab())

    return kept(("ranks", path, pattern), make)


class ByteTable:
    """Strings by id, joined for many ids at once: the bytes of tokens, or their decimal names."""

    def __init__(self, vocab: dict[str, int]):
        """vocab: names of tokens in the characters that stand for bytes; the table of those characters is read backwards."""
        byte = {c: b for b, c in enumerate(byte_chars())}
        n = max(vocab.values(), default=-1) + 1
        token = [b""] * n
        for k, v in vocab.items():
            token[v] = bytes(byte[c] for c in k)
        self.token, self.decimal = self._table(token), self._table([b"%d " % i for i in range(n)])

    @staticmethod
    def _table(parts: list[bytes]):
        size = np.fromiter(map(len, parts), np.int64, len(parts))
        return np.frombuffer(b"".join(parts), np.uint8), np.cumsum(size) - size, size

    @staticmethod
    def join(table, ids: np.ndarray) -> np.ndarray:
        flat, start, size = table
        return flat[ranges(start[ids], size[ids])]

    def decode(self, ids: np.ndarray) -> bytes:
        """The bytes of the ids; whole even where one character is split over ids."""
        return self.join(self.token, np.asarray(ids, np.int64)).tobytes()

    def decode_text(self, ids: np.ndarray) -> str:
        """Text of the ids; a character whose bytes are not all there becomes U+FFFD."""
        return self.decode(ids).decode("utf-8", errors="replace")

    def decode_stream(self, parts):
        """Text of id chunks as they come: the bytes of a split character wait for the next chunk."""
        import codecs

        reader = codecs.getincrementaldecoder("utf-8")("replace")
        for ids in parts:
            yield reader.decode(self.decode(ids))
        yield reader.decode(b"", final=True)

    def byte_offsets(self, ids: np.ndarray) -> np.ndarray:
        """n + 1 offsets of the ids' bytes in the decoded bytes."""
        return np.concatenate(([0], np.cumsum(self.token[2][np.asarray(ids, np.int64)])))
