"""Token ids of whole texts with a public word-level BPE, each different run of letters or marks encoded once.

The vocabulary file replaces white space by one space, lower-cases character by character and splits
into letter runs, digits and symbol runs, so no token crosses one of these: the ids of a text are the
ids of its runs in turn. The runs are found in the bytes of a batch as arrays; each worker keeps a
bounded table run -> ids, which the tokenizer fills.
"""

from __future__ import annotations

import codecs
from array import array
from collections.abc import Iterator
from itertools import repeat

import numpy as np

SPACE, LETTER, SYMBOL, DIGIT, ODD = range(5)
_LEAD = 0xC3  # first byte of the Latin letters from U+00C0 to U+00FF


def _tables() -> tuple[np.ndarray, np.ndarray]:
    """By byte: its kind and its lower case. The quote and ``<`` are odd: contractions and special tokens begin with them."""
    kinds, lower = np.full(256, ODD, np.uint8), np.arange(256, dtype=np.uint8)
    kinds[33:127] = SYMBOL
    kinds[[9, 10, 11, 12, 13, 32]] = SPACE
    kinds[ord("0") : ord("9") + 1] = DIGIT
    kinds[[ord("'"), ord("<")]] = ODD
    for first, last in (("A", "Z"), ("a", "z")):
        kinds[ord(first) : ord(last) + 1] = LETTER
    kinds[_LEAD] = LETTER
    lower[ord("A") : ord("Z") + 1] += 32
    return kinds, lower


_KINDS, _LOWER = _tables()


def _byte_letters() -> str:
    """By byte: the character that stands for it in a byte-level vocabulary; a space stays one and parts words."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = {b: chr(256 + k) for k, b in enumerate(b for b in range(256) if b not in own)}
    return "".join(" " if b == 32 else other.get(b, chr(b)) for b in range(256))


_BYTE_LETTERS = _byte_letters()


def _spelled(words: bytes) -> str:
    return codecs.charmap_decode(words, "strict", _BYTE_LETTERS)[0]


def _ranges(n: int, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Which of ``n`` places lie in one of the ranges."""
    step = np.zeros(n + 1, np.int8)
    step[starts] += 1
    step[ends] -= 1
    return np.cumsum(step[:-1], dtype=np.int8) > 0


def runs(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The runs of UTF-8 texts (``data`` from ``offsets[i]`` to ``offsets[i + 1]``): their bytes without white space, their starts there, their kinds, and the number of runs before each offset.

    A run is lower-case letters, one digit, or symbols. What lies between white space and holds any other
    character than these of ASCII and Latin-1 is one odd run, as it stands.
    """
    n = len(data)
    kind, low = _KINDS[data], _LOWER[data]
    after = np.flatnonzero(data[:-1] == _LEAD) + 1
    second = data[after]
    latin = (second & 0xC0 == 0x80) & (second != 0x97) & (second != 0xB7)  # not the signs of multiplication and division
    kind[after[latin]] = LETTER
    low[after[latin & (second <= 0x9E)]] += 32
    heads = offsets[:-1][offsets[:-1] < n]
    kind[after[~latin] - 1] = ODD
    kind[heads[data[heads] & 0xC0 == 0x80]] = ODD  # no text begins or ends like this in UTF-8; decoding will say so
    if data[-1] == _LEAD:
        kind[-1] = ODD
    begin = np.ones(n, bool)
    np.not_equal(kind[1:], kind[:-1], out=begin[1:])
    begin |= kind == DIGIT
    begin[heads] = True
    solid = kind != SPACE
    odd = np.flatnonzero(kind == ODD)
    if len(odd):
        first, last = solid.copy(), solid.copy()
        first[1:] &= ~solid[:-1]
        first[heads] = solid[heads]
        last[:-1] &= ~solid[1:]
        tails = offsets[1:][offsets[1:] > 0] - 1
        last[tails] = solid[tails]
        starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
        hit = np.unique(np.searchsorted(starts, odd, side="right") - 1)
        inside = _ranges(n, starts[hit], ends[hit])
        low[inside], kind[inside], begin[inside] = data[inside], ODD, False
        begin[starts[hit]] = True
    before = np.searchsorted(np.flatnonzero(begin & solid), offsets)
    at = np.flatnonzero(begin[solid])
    return low[solid], at, kind[solid][at], before


class WordEncoder:
    """Encodes texts to little-endian unsigned 32-bit ids. ``limit`` bounds the table, ``longest`` the bytes of the runs kept in it.

    Unseen letter runs go to the vocabulary's merges many at a time, as byte letters with spaces between; each ends with a token that closes a word.
    """

    def __init__(self, path: str, limit: int = 500_000, longest: int = 48, together: int = 1000):
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer, self.letters = Tokenizer.from_file(path), Tokenizer(Tokenizer.from_file(path).model)
        self.letters.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        vocab, suffix = self.tokenizer.get_vocab(), getattr(self.tokenizer.model, "end_of_word_suffix", None)
        self.closing = np.zeros(max(vocab.values(), default=0) + 1, bool)
        self.closing[[i for token, i in vocab.items() if suffix and token.endswith(suffix)]] = True
        self.limit, self.longest, self.together = limit, longest, together
        self.forget()

    def forget(self) -> None:
        self.known: dict[bytes, int] = {}
        self.ids, self.ends = np.empty(0, "<u4"), np.zeros(1, np.int64)

    def _single(self, tokenizer, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        made = [made.ids for i in range(0, len(words), 20_000) for made in tokenizer.encode_batch_fast(words[i : i + 20_000], add_special_tokens=False)]
        ids = array("I")
        for x in made:
            ids.extend(x)
        return np.array(ids, "<u4"), np.fromiter(map(len, made), np.int64, len(made))

    def _joined(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        ids = array("I")
        for i in range(0, len(words), self.together):
            ids.extend(self.letters.encode_batch_fast([_spelled(b" ".join(words[i : i + self.together]))], add_special_tokens=False)[0].ids)
        flat = np.array(ids, "<u4")
        ends = np.flatnonzero(self.closing[flat]) + 1
        if len(ends) != len(words) or len(words) and ends[-1] != len(flat):
            return self._single(self.letters, [_spelled(w) for w in words])
        return flat, np.diff(ends, prepend=0)

    def _learn(self, words: list[bytes], letters: np.ndarray) -> None:
        """Adds the ids of unseen runs: those of letters, then the others."""
        plain, rest = [w for w, x in zip(words, letters, strict=True) if x], [w for w, x in zip(words, letters, strict=True) if not x]
        a, b = self._joined(plain), self._single(self.tokenizer, [w.decode() for w in rest])
        n = len(self.ends) - 1
        self.known.update(zip([*plain, *rest], range(n, n + len(words)), strict=True))
        self.ids = np.concatenate([self.ids, a[0], b[0]])
        self.ends = np.concatenate([self.ends, self.ends[-1] + np.cumsum(np.concatenate([a[1], b[1]]))])

    def encode_bytes(self, data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
        """The ids of each text; the texts lie in ``data``, UTF-8, from ``offsets[0]``, which is 0, to ``offsets[-1]``, its end."""
        import pyarrow as pa

        if not len(data):
            return [b""] * (len(offsets) - 1)
        if len(self.known) > self.limit or len(self.ids) > 16 * self.limit:
            self.forget()
        packed, at, kind, before = runs(data, offsets)
        offset = np.append(at, len(packed))
        values = pa.Array.from_buffers(pa.large_binary(), len(at), [None, pa.py_buffer(offset), pa.py_buffer(packed)]).dictionary_encode()
        which, words = values.indices.to_numpy(), values.dictionary.to_numpy(zero_copy_only=False).tolist()
        kinds = np.empty(len(words), np.uint8)
        kinds[which] = kind
        place = np.fromiter(map(self.known.get, words, repeat(-1)), np.int64, len(words))
        unseen = np.flatnonzero(place < 0)
        if len(unseen):
            new = [words[i] for i in unseen.tolist()]
            self._learn(new, kinds[unseen] == LETTER)
            place[unseen] = np.fromiter(map(self.known.__getitem__, new), np.int64, len(new))
            for word in new:
                if len(word) > self.longest:
                    del self.known[word]
        place = place[which]
        start = self.ends[place]
        size = self.ends[place + 1] - start
        ends = np.zeros(len(size) + 1, np.int64)
        np.cumsum(size, out=ends[1:])
        ids = self.ids[np.repeat(start - ends[:-1], size) + np.arange(ends[-1])].tobytes()
        cuts = (4 * ends[before]).tolist()
        return [ids[a:b] for a, b in zip(cuts, cuts[1:])]

    def encode(self, texts: list[str]) -> list[bytes]:
        raw = [t.encode() for t in texts]
        return self.encode_bytes(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    """One encoder a worker process."""
    if path not in _encoders:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encoded_batches(batches: Iterator, path: str, id_col: str, text_col: str, bytes_at_once: int = 4_000_000) -> Iterator[tuple[list, list[bytes]]]:
    """From Arrow batches, lists of ids and of encoded texts; a few MB of text at a time."""
    enc = encoder(path)
    try:
        yield from _encoded(enc, batches, id_col, text_col, bytes_at_once)
    finally:
        enc.forget()  # other operators use the same worker after this task


def _encoded(enc: WordEncoder, batches: Iterator, id_col: str, text_col: str, bytes_at_once: int) -> Iterator[tuple[list, list[bytes]]]:
    import pyarrow as pa

    for batch in batches:
        ids, texts = batch.column(id_col).to_pylist(), batch.column(text_col).cast(pa.large_string()).fill_null("")
        _, places, held = texts.buffers()
        offsets = np.frombuffer(places, np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
        data = np.frombuffer(held, np.uint8) if held is not None else np.empty(0, np.uint8)
        at = 0
        while at < len(ids):
            to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + bytes_at_once, side="right")) - 1)
            yield ids[at:to], enc.encode_bytes(data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
            at = to
