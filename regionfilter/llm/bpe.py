"""Byte-level BPE that gives the tokenizers library's ids, by tree concatenation and faster on repeated text.

``encode_trees`` halves a long text, wherever the middle falls, until its parts are ``leaf`` characters at most. The
leaves know nothing of each other and are encoded together, in parallel as far as the caller likes. Then neighbours
are joined level by level: a window of tokens around each join is encoded anew, and grows until it agrees with both
sides on the tokens at its ends, so that what lies beyond stands. Three facts about the pre-tokenizer's pattern carry
this. No alternative of it takes a character that is not white space followed by one that is, so a window may begin or
end there ("chunks": white space and the word after it). Inside one pre-token, a sequence of tokens is the BPE encoding
as soon as each neighbouring pair of it lies in some valid encoding, so a window may also begin or end between two
characters of a kind. Strings of special tokens are taken out before anything else.

Short parts are encoded by chunks, which are looked up in a bounded cache; the missing ones go to the library many at
a time. ``encode_many`` does this with whole texts, for operators that only need ids, and grows a tree where a text has
no white space for longer than a leaf.
"""

from __future__ import annotations

import hashlib
import re
from itertools import chain

import numpy as np
import public_tokenizers
import regex
from tokenizers import Tokenizer

TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")
#: most characters of a leaf of the tree
LEAF = 1024
#: chunks remembered by a worker, in two generations
CACHE = 350_000
#: characters of texts that are in chunks at the same time, about
SLICE = 1 << 20
CHUNK = re.compile(r"[ \t\n\r\f\v]*[^ \t\n\r\f\v]+|[ \t\n\r\f\v]+")
#: white space beside the six of ASCII, under any definition: then a cut needs a look at what stands before it
ODD_SPACE = re.compile(r"[\x1c-\x1f\x85\xa0\u1680\u180e\u2000-\u200b\u2028\u2029\u202f\u205f\u3000\ufeff]")
STRICT_CUT = re.compile(r"(?<=[^\s\u180e\u200b\ufeff])(?=[ \t\n\r\f\v])")
#: a chunk of letters and marks: two pre-tokens at most, so that words share their ids whatever marks follow
PLAIN = re.compile(r"( ?[A-Za-z\u00df-\u00f6\u00f8-\u00ff]+)([.,;:!?]*)")
LETTER, NUMBER = regex.compile(r"\p{L}"), regex.compile(r"\p{N}")


def tokenizer_digest(path: str = TOKENIZER) -> str:
    """Version of a tokenizer: SHA-256 of its file."""
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


class Encoder:
    """encode() and decode() of a byte-level BPE file, by chunk cache and tree."""

    def __init__(self, path: str = TOKENIZER, leaf: int = LEAF, cache: int = CACHE):
        self.library = Tokenizer.from_file(path)
        self.leaf, self.limit = leaf, cache // 2
        self.known: dict[str, bytes] = {}
        self.before: dict[str, bytes] = {}  # the generation before: what of it is met again moves on, the rest goes
        self.special = {t.content: i for i, t in self.library.get_added_tokens_decoder().items()}
        self.special_cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        of_char = {c: b for b, c in enumerate(_byte_chars())}
        self.char_of, self.model = {b: c for c, b in of_char.items()}, self.library.model
        self.packed_of = [i.to_bytes(4, "little") for i in range(self.library.get_vocab_size())]
        #: whether the library does nothing but split and merge, so that a pre-token may go to its model at once
        self.direct = self.library.normalizer is None and all(
            np.array(self.library.encode(x + y, add_special_tokens=False).ids, dtype="<u4").tobytes() == self._merged(x) + self._merged(y) for x, y in (("word", ""), (" word", ""), (" word", ".,"), ("Été", "!"))
        )
        size = self.library.get_vocab_size()
        self.bytes_of = [t.encode() if (t := self.library.id_to_token(i)) in self.special else bytes(of_char[c] for c in t) for i in range(size)]
        self.length_of = np.array([len(b) for b in self.bytes_of], dtype=np.int64)
        self.decimal_of = [str(i) for i in range(size)]

    def encode_many(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit numbers; some texts at a time, for their chunks are
        many small strings."""
        out, begin, size = [], 0, 0
        for i, t in enumerate(texts):
            size += len(t)
            if size >= SLICE or i + 1 == len(texts):
                out += self._encode_slice(texts[begin : i + 1])
                begin, size = i + 1, 0
        return out

    def _encode_slice(self, texts: list[str]) -> list[bytes]:
        chunks = [self.chunks(t) for t in texts]
        need = set()
        for c in chunks:
            need.update(c)
        if len(self.known) > self.limit:
            self.before, self.known = self.known, {}
        need = {c for c in need if c not in self.known}
        again = {c for c in need if c in self.before}
        self.known.update((c, self.before[c]) for c in again)
        need -= again
        if need:
            self._learn(list(need))
        look = self.known.__getitem__
        return [b"".join(map(look, c)) for c in chunks]

    def encode_trees(self, texts: list[str]) -> list[tuple[bytes, int]]:
        """(ids, joins) of each text, by the tree. The leaves of all texts are encoded together: the library is asked in bulk."""
        parts = [[(p, [p] if p in self.special else self._leaves(p)) for p in self._parts(t)] for t in texts]
        encoded, out = iter(self.encode_many([x for of in parts for _, leaves in of for x in leaves])), []
        for of in parts:
            ids, joins = [], 0
            for p, leaves in of:
                if len(leaves) == 1:
                    ids.append(next(encoded))
                else:
                    whole, made = self._joined(p, leaves, [np.frombuffer(next(encoded), dtype="<u4") for _ in leaves])
                    ids.append(whole.astype("<u4").tobytes())
                    joins += made
            out.append((b"".join(ids), joins))
        return out

    def encode_tree(self, text: str) -> tuple[bytes, int]:
        """The ids of a text, and how many joins were made."""
        return self.encode_trees([text])[0]

    def _parts(self, text: str) -> list[str]:
        """A text cut at special strings."""
        return [p for p in self.special_cut.split(text) if p] if self.special_cut and any(s in text for s in self.special) else [text]

    def _leaves(self, run: str) -> list[str]:
        """Halves of halves of a text, until they are short."""
        cuts = [0, len(run)]
        while cuts[1] - cuts[0] > self.leaf:
            cuts = sorted({*cuts, *((a + b) // 2 for a, b in zip(cuts, cuts[1:]))})
        return [run[a:b] for a, b in zip(cuts, cuts[1:])]

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_many([text])[0], dtype="<u4").tolist()

    def decode(self, ids) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")

    def chunks(self, text: str) -> list[str]:
        if self.special_cut and any(s in text for s in self.special):
            parts = self.special_cut.split(text)
            return list(chain.from_iterable([p] if p in self.special else self._plain_chunks(p) for p in parts if p))
        return self._plain_chunks(text)

    @staticmethod
    def _plain_chunks(text: str) -> list[str]:
        if ODD_SPACE.search(text):
            return [c for c in STRICT_CUT.split(text) if c]
        return CHUNK.findall(text)

    def _merged(self, pretoken: str) -> bytes:
        """The packed ids of one pre-token, by the library's model."""
        shown = pretoken.encode().decode("latin-1").translate(self.char_of) if not pretoken.isascii() or pretoken[:1] != " " else self.char_of[32] + pretoken[1:]
        return b"".join([self.packed_of[t.id] for t in self.model.tokenize(shown)])

    def _learn_plain(self, chunk: str, word: str, marks: str) -> None:
        known = self.known
        if word not in known:
            known[word] = self.before.get(word) or self._merged(word)
        if marks:
            if marks not in known:
                known[marks] = self._merged(marks)
            known[chunk] = known[word] + known[marks]

    def _learn(self, chunks: list[str]) -> None:
        joined, alone = [], []
        for c in chunks:
            if self.direct and len(c) <= self.leaf and (plain := PLAIN.fullmatch(c)):
                self._learn_plain(c, *plain.groups())
            elif c in self.special:
                self.known[c] = np.array([self.special[c]], dtype="<u4").tobytes()
            elif len(c) > self.leaf:
                self.known[c] = self._tree(c)[0].astype("<u4").tobytes()
            elif c[0] in " \t\n\r\f\v" and not c[-1].isspace() and not ODD_SPACE.search(c):
                joined.append(c)  # cuts before and after it hold in any company of its kind
            else:
                alone.append(c)
        for i in range(0, len(joined), 4096):
            self._learn_joined(joined[i : i + 4096])
        for c, ids in zip(alone, self._ids_of(alone), strict=True):
            self.known[c] = np.array(ids, dtype="<u4").tobytes()

    def _learn_joined(self, chunks: list[str]) -> None:
        ids = np.array(self._ids_of(["".join(chunks)])[0], dtype="<u4")
        ends = np.cumsum(self.length_of[ids])
        cuts = np.searchsorted(ends, np.cumsum([len(c.encode()) for c in chunks]), side="left") + 1
        start = 0
        for c, end in zip(chunks, cuts.tolist(), strict=True):
            self.known[c] = ids[start:end].tobytes()
            start = end

    def _tree(self, run: str) -> tuple[np.ndarray, int]:
        """The ids of a text without special strings: leaves first, all together, then joins level by level."""
        leaves = self._leaves(run)
        return self._joined(run, leaves, [self._leaf(t) for t in leaves])

    def _joined(self, run: str, leaves: list[str], encoded: list[np.ndarray]) -> tuple[np.ndarray, int]:
        """The ids of a text from those of its leaves, and how many joins were made."""
        data, at, ends = run.encode(), 0, []
        for t in leaves:
            at += len(t.encode())
            ends.append(at)
        level, joins = list(zip(encoded, ends, strict=True)), 0
        while len(level) > 1:
            joins += len(level) // 2
            level = [(self._join(data, level[i][0], level[i][1], level[i + 1][0]), level[i + 1][1]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
        return level[0][0], joins

    def _leaf(self, text: str) -> np.ndarray:
        """The ids of a leaf or a window: by chunks, unless one chunk of it is longer than a leaf."""
        chunks = self.chunks(text)
        if max(map(len, chunks)) < self.leaf:
            return np.frombuffer(self._encode_slice([text])[0], dtype="<u4")
        return np.array(self._ids_of([text])[0], dtype="<u4")

    def _ids_of(self, texts: list[str]) -> list[list[int]]:
        """The library's ids; few texts one by one, for its batches start threads."""
        if len(texts) < 8 and sum(map(len, texts)) < 4096:
            return [self.library.encode(t, add_special_tokens=False).ids for t in texts]
        return [e.ids for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _join(self, data: bytes, a: np.ndarray, middle: int, b: np.ndarray) -> np.ndarray:
        """The ids of two neighbouring parts of data that meet at ``middle``."""
        width, size = 4, self.length_of
        while True:
            i, j = max(0, len(a) - width), min(len(b), width)
            begin, end = middle - int(size[a[i:]].sum()), middle + int(size[b[:j]].sum())
            while i > 0 and not _edge(data, begin):
                i -= 1
                begin -= int(size[a[i]])
            while j < len(b) and not _edge(data, end):
                end += int(size[b[j]])
                j += 1
            ids = self._leaf(data[begin:end].decode())
            whole = i == 0 and j == len(b)
            if whole or len(ids) > 1 and (i == 0 or ids[0] == a[i]) and (j == len(b) or ids[-1] == b[j - 1]):
                return np.concatenate([a[:i], ids, b[j:]])
            width *= 2


def _edge(data: bytes, at: int) -> bool:
    """Whether a window may begin or end at this byte: before white space that follows something else, or inside one
    kind of characters, where the split into pre-tokens does not depend on what stands further away."""
    if at >= len(data) or data[at] & 0xC0 == 0x80:
        return False
    before = data[max(0, at - 4) : at].decode("utf-8", "ignore")[-1:]
    after = data[at : at + 4].decode("utf-8", "ignore")[:1]
    if not before or not after or before.isspace() or ODD_SPACE.search(before + after):
        return False
    if after in " \t\n\r\f\v":
        return True
    if after.isspace() or b"'" in data[max(0, at - 16) : at + 16]:
        return False
    kinds = [1 if LETTER.match(c) else 2 if NUMBER.match(c) else 3 for c in (before, after)]
    return kinds[0] == kinds[1]


def _byte_chars() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(hidden)) for b in range(256)]


_ENCODERS: dict[tuple[str, int], Encoder] = {}


def encoder(path: str = TOKENIZER, cache: int = CACHE) -> Encoder:
    """The worker's encoder of a file that remembers so many chunks, loaded once."""
    if (path, cache) not in _ENCODERS:
        _ENCODERS[path, cache] = Encoder(path, cache=cache)
    return _ENCODERS[path, cache]
