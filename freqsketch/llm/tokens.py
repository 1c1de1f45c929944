"""Exact byte-level BPE ids of whole texts at memory-bandwidth speed.

The ``tokenizers`` library encodes each distinct word once; words are cut from the text and
looked up in a bounded cache with vectorised code. The result is that of encoding every whole
text with the library (tests compare them): byte-level BPE never merges across the words of
its pattern, so a text's ids are those of its words, joined.
"""

from __future__ import annotations

import unicodedata
from functools import cache, cached_property

import numpy as np

from .common import mix64, powers

OTHER, LETTER, NUMBER, BLANK, UNSURE = range(5)
#: White space in the sense of the word pattern.
WHITE = [*range(9, 14), 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
#: Endings that the word pattern cuts off after an apostrophe.
SHORT = ("s", "t", "m", "d")
LONG = ("re", "ve", "ll")

SLOT_BITS = 21
#: The cache starts anew when it holds so many ids.
STORE_IDS = 4_000_000
APOSTROPHE = 0x27


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@cache
def _classes() -> np.ndarray:
    """Class of each code point; UNSURE where Unicode versions differ."""
    table = np.zeros(0x110000, np.uint8)
    old = unicodedata.ucd_3_2_0
    for c in range(0x110000):
        if 0xD800 <= c < 0xE000:
            continue
        ch = chr(c)
        now = unicodedata.category(ch)
        if now == "Co" or now == "Cn" and c > 0xE0FFF:
            continue
        if now[0] != old.category(ch)[0]:
            table[c] = UNSURE
        elif now[0] == "L":
            table[c] = LETTER
        elif now[0] == "N":
            table[c] = NUMBER
    table[WHITE] = BLANK
    return table


def word_starts(chars: np.ndarray, firsts: np.ndarray) -> np.ndarray:
    """Starts of the words of the byte-level pattern in texts that begin at ``firsts``.

    A word is an ending after an apostrophe, or a run of letters, of digits or of other signs
    with one space before it, or white space: of a run that ends at a sign the last character
    stands apart.
    """
    n = len(chars)
    kind = _classes()[chars]
    first = np.zeros(n + 1, bool)
    first[firsts[firsts < n]] = True
    first[n] = True
    change = np.ones(n, bool)
    change[1:] = kind[1:] != kind[:-1]
    blank = kind == BLANK
    start = change | first[:n]
    # a sign after a space takes the space in
    inner = ~first[1:n]
    start[1:] &= ~(inner & (chars[:-1] == 32) & ~blank[1:])
    # the last of a run of white space, where a sign of the same text follows
    start[:-1] |= blank[:-1] & ~blank[1:] & inner
    at = np.flatnonzero((chars[:-1] == APOSTROPHE) & start[:-1] & inner) if n > 1 else np.zeros(0, int)
    if len(at):
        c1 = chars[at + 1]
        ends = np.zeros(len(at), np.int64)
        ends[np.isin(c1, [ord(x) for x in SHORT])] = 2
        two = (at + 2 < n) & ~first[np.minimum(at + 2, n)]
        c2 = chars[np.minimum(at + 2, n - 1)]
        for x in LONG:
            ends[(c1 == ord(x[0])) & two & (c2 == ord(x[1]))] = 3
        hit = at[ends > 0]
        start[hit + 1] = False
        after = hit + ends[ends > 0]
        start[after[after < n]] = True
    return np.flatnonzero(start)


class WordEncoder:
    """Ids of texts; one for each Python worker and vocabulary file.

    The names of special tokens in a text become these tokens, as they do in the library;
    with ``escape`` they are plain text, so that no text yields a special id."""

    def __init__(self, path: str, escape: bool = False):
        from tokenizers import Tokenizer, pre_tokenizers

        self.path = path
        self.words = Tokenizer.from_file(path)
        self.special = [] if escape else [t.content for t in self.words.get_added_tokens_decoder().values()]
        self.words.encode_special_tokens = True
        self.words.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in set(plain)]
        # the alphabet of byte-level vocabularies; 255 is in no UTF-8 text and parts the words
        self.alphabet = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}
        self.alphabet[255] = " "
        size = self.words.get_vocab_size()
        self.id_bytes = np.array([len(self.words.id_to_token(i) or "") for i in range(size)], np.int64)
        self._reset()

    @cached_property
    def whole(self):
        """The library's tokenizer as it is; few texts need it."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def _reset(self) -> None:
        self.keys = np.zeros(1 << SLOT_BITS, np.uint64)
        self.slots = np.zeros(1 << SLOT_BITS, np.int32)
        self.begin = np.zeros(1 << 16, np.int64)
        self.length = np.zeros(1 << 16, np.int32)
        self.n_words = 0
        self.ids = np.zeros(1 << 18, np.uint32)
        self.n_ids = 0

    def _grow(self, words: int, ids: int) -> None:
        while self.n_words + words > len(self.begin):
            self.begin = np.concatenate([self.begin, np.zeros_like(self.begin)])
            self.length = np.concatenate([self.length, np.zeros_like(self.length)])
        while self.n_ids + ids > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])

    def _learn(self, words: list[str]) -> np.ndarray:
        """Encode words with the library; their places in the store."""
        raw = [w.encode() for w in words]
        joined = b"\xff".join(raw).decode("latin-1").translate(self.alphabet)
        ids = np.array(self.words.encode_batch_fast([joined], add_special_tokens=False)[0].ids, np.uint32)
        ends = np.searchsorted(np.cumsum(self.id_bytes[ids]), np.cumsum([len(r) for r in raw])) + 1
        lens = np.diff(ends, prepend=0)
        self._grow(len(words), len(ids))
        places = np.arange(self.n_words, self.n_words + len(words))
        self.begin[places] = self.n_ids + ends - lens
        self.length[places] = lens
        self.ids[self.n_ids : self.n_ids + len(ids)] = ids
        self.n_words += len(words)
        self.n_ids += len(ids)
        return places

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, joined (uint32), and each text's number of ids."""
        text = "".join(texts)
        lens = np.array([len(t) for t in texts], np.int64)
        counts = np.zeros(len(texts), np.int64)
        if not text:
            return np.zeros(0, np.uint32), counts
        chars = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        if (_classes()[chars] == UNSURE).any() or any(t in text for t in self.special):
            return self._encode_whole(texts)
        if self.n_ids > STORE_IDS:
            self._reset()
        firsts = np.cumsum(lens) - lens
        starts = word_starts(chars, firsts)
        wlen = np.diff(starts, append=len(chars))
        pos = np.arange(len(chars)) - np.repeat(starts, wlen)
        h = np.add.reduceat((chars.astype(np.uint64) + np.uint64(1)) * powers(int(wlen.max()) + 1)[pos], starts)
        h = mix64(h + wlen.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
        slot = (h >> np.uint64(64 - SLOT_BITS)).astype(np.int64)
        place = self.slots[slot].astype(np.int64)
        miss = np.flatnonzero(self.keys[slot] != h)
        if len(miss):
            _, one, back = np.unique(h[miss], return_index=True, return_inverse=True)
            at = miss[one]
            learned = self._learn([text[s : s + w] for s, w in zip(starts[at].tolist(), wlen[at].tolist())])
            place[miss] = learned[back]
            self.keys[slot[at]] = h[at]
            # where two new words share a slot the last one written stays, key and place alike
            self.slots[slot[at]] = learned
        n = self.length[place].astype(np.int64)
        ends = np.cumsum(n)
        out = self.ids[np.arange(int(ends[-1])) + np.repeat(self.begin[place] - (ends - n), n)]
        total = np.concatenate([[0], ends])
        edge = np.searchsorted(starts, np.append(firsts, len(chars)))
        counts = np.diff(total[edge])
        return out, counts

    def _encode_whole(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Texts with special tokens or characters that are new to Unicode go through the library as
        they are; the others, one by one, through the cache."""
        ids, counts = [], np.zeros(len(texts), np.int64)
        whole = self.whole
        whole.encode_special_tokens = not self.special
        for i, t in enumerate(texts):
            other = (_classes()[np.frombuffer(t.encode("utf-32-le"), np.uint32)] == UNSURE).any() or any(x in t for x in self.special)
            got = np.array(whole.encode(t, add_special_tokens=False).ids, np.uint32) if other else self.encode([t])[0]
            ids.append(got)
            counts[i] = len(got)
        return np.concatenate(ids), counts


@cache
def encoder(path: str, escape: bool = False) -> WordEncoder:
    return WordEncoder(path, escape)


def id_type(path: str) -> np.dtype:
    return np.dtype("<u2") if encoder(path).words.get_vocab_size() <= 1 << 16 else np.dtype("<u4")


def with_ids(df, text: str, keep: list[str], path: str, slice_bytes: int = 500_000, watch=None):
    """Columns of ``keep`` and ``ids``: each whole text's ids, raw little-endian, two bytes an
    id where the vocabulary allows it, else four. Null texts have no ids. ``watch()`` makes, in each
    task, an object whose ``add(ids, counts)`` sees all of its ids and whose ``close()`` ends it."""
    import pyarrow as pa
    from pyspark.sql import functions as F

    from .common import binary_array, byte_slices, text_buffer, tidy

    picked = df.select(*keep, F.col(text).alias("_text"))
    fields = [f for f in picked.schema.fields if f.name != "_text"]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + ["ids binary"])

    def run(batches):
        enc, kind = encoder(path), id_type(path)
        seen = watch() if watch else None
        for b in batches:
            col = b.column(b.schema.get_field_index("_text"))
            _, off = text_buffer(col)
            for lo, hi in byte_slices(off, slice_bytes):
                part = b.slice(lo, hi - lo)
                ids, counts = enc.encode([t or "" for t in col.slice(lo, hi - lo).to_pylist()])
                if seen:
                    seen.add(ids, counts)
                yield pa.RecordBatch.from_arrays(
                    [part.column(part.schema.get_field_index(f.name)) for f in fields] + [binary_array(ids.astype(kind), counts)],
                    [f.name for f in fields] + ["ids"],
                )
        if seen:
            seen.close()

    return picked.mapInArrow(tidy(run), schema)
