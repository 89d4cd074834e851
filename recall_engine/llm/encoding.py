"""Fast exact encoding with a public tokenizer: texts are cut where tokens can't cross, and each distinct piece is encoded once."""

from __future__ import annotations

import os
import sys
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from . import textkit

#: White space beyond ASCII: a text that has any of it is encoded whole.
WIDE_SPACE = r"[\x{85}\x{A0}\x{1680}\x{2000}-\x{200A}\x{2028}\x{2029}\x{202F}\x{205F}\x{3000}]"
#: Of each byte: 1 for an ASCII letter, 2 for other printable ASCII but digits and the space, 3 for the first byte of any wide space, else 0.
_KIND = np.array([1 if chr(b).isalpha() and b < 128 else 2 if 32 < b < 127 and not chr(b).isdigit() else 3 if b in (0xC2, 0xE1, 0xE2, 0xE3) else 0 for b in range(256)], np.uint8)
#: Distinct pieces kept per worker; then the memory starts anew.
REMEMBERED = 1_000_000


def default_tokenizer(name: str) -> str:
    """The path of a public tokenizer's file, where its package is installed."""
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """Encodes texts as the library does with add_special_tokens=False. With ``special_as_text`` the strings of special
    tokens inside texts count as text; without, as in the library's plain call, they become the special ids, and texts
    that have any are encoded whole.

    Both kinds of tokenizer here split a text so that no token holds a non-space character followed by a space, or an
    ASCII letter followed by ASCII punctuation. Cuts before each run of ASCII white space that follows another
    character, and before punctuation that follows an ASCII letter, therefore change no token.
    """

    def __init__(self, path: str, special_as_text: bool = False):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = special_as_text
        added = self.library.get_added_tokens_decoder().values()
        self.added = [t.content for t in added if not (special_as_text and t.special)]
        self.forget()

    def forget(self) -> None:
        # Pieces are known by a 128-bit hash, sorted by its first half: a tenth of the memory that their strings would take.
        self.first, self.second, self.place = (np.zeros(0, t) for t in (np.uint64, np.uint64, np.int64))
        self.flat, self.bounds = np.zeros(0, np.uint32), np.zeros(1, np.int64)

    @staticmethod
    def shared(path: str, special_as_text: bool = False) -> Encoder:
        """One encoder per worker process, path and way with special tokens."""
        kept = sys.modules.setdefault("_recall_engine_encoders", type(sys)("_recall_engine_encoders")).__dict__
        key = f"{path} {special_as_text}"
        if key not in kept:
            kept[key] = Encoder(path, special_as_text)
        return kept[key]

    def whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: list[bytes]) -> np.ndarray:
        """The number of each of these distinct pieces; new ones are encoded."""
        if len(self.place) > REMEMBERED:
            self.forget()
        import xxhash

        key = np.frombuffer(b"".join(map(xxhash.xxh3_128_digest, pieces)), "<u8").reshape(-1, 2)
        one, two = np.ascontiguousarray(key[:, 0]), np.ascontiguousarray(key[:, 1])
        at = np.searchsorted(self.first, one)
        number = np.full(len(pieces), -1, np.int64)
        if len(self.first):
            spot = np.minimum(at, len(self.first) - 1)
            known = (self.first[spot] == one) & (self.second[spot] == two)
            number[known] = self.place[spot[known]]
        new = np.flatnonzero(number < 0)
        if len(new):
            ids = self.whole([pieces[i].decode() for i in new.tolist()])
            number[new] = len(self.bounds) - 1 + np.arange(len(new))
            self.bounds = np.concatenate([self.bounds, self.bounds[-1] + np.cumsum([len(x) for x in ids])])
            self.flat = np.concatenate([self.flat, np.fromiter(chain.from_iterable(ids), np.uint32)])
            new = new[np.argsort(one[new])]
            self.first, self.second, self.place = (np.insert(old, at[new], x[new]) for old, x in ((self.first, one), (self.second, two), (self.place, number)))
        return number

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after another (uint32), and each text's bounds (n + 1)."""
        texts = texts.cast(pa.large_string()).fill_null("")
        raw, off = textkit.string_buffers(texts)
        kind = _KIND[raw]
        odd = np.zeros(len(texts), bool)
        if (kind == 3).any():
            odd |= pc.match_substring_regex(texts, WIDE_SPACE).to_numpy(zero_copy_only=False)
        for token in self.added:
            odd |= pc.match_substring(texts, token).to_numpy(zero_copy_only=False)
        if odd.any():
            raw, off = textkit.string_buffers(pc.if_else(pa.array(odd), "", texts))
            kind = _KIND[raw]
        space = textkit.space_mask(raw)
        cut = np.zeros(len(raw) + 1, bool)
        cut[1:-1] = (space[1:] & ~space[:-1]) | ((kind[1:] == 2) & (kind[:-1] == 1))
        cut[off[:-1][np.diff(off) > 0]] = True
        starts = np.flatnonzero(cut)
        ends = np.append(starts, len(raw)).astype(np.int64)
        pieces = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(raw))])
        ids, values = textkit.codes(pieces)
        known = self._learn(values.to_pylist())
        bounds, flat = self.bounds, self.flat
        first = known[ids] if len(ids) else ids
        lengths = bounds[first + 1] - bounds[first]
        out = flat[_ragged(bounds[first], lengths)]
        upto = np.concatenate([[0], np.cumsum(lengths)])[np.searchsorted(starts, off)]
        if odd.any():
            return self._mixed(texts, odd, out, upto)
        return out, upto

    def _mixed(self, texts: pa.Array, odd: np.ndarray, out: np.ndarray, upto: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        own = dict(zip(np.flatnonzero(odd).tolist(), self.whole(texts.filter(pa.array(odd)).to_pylist()), strict=True))
        parts = [np.asarray(own[i], np.uint32) if odd[i] else out[upto[i] : upto[i + 1]] for i in range(len(odd))]
        return np.concatenate(parts), np.concatenate([[0], np.cumsum([len(p) for p in parts])])


def _ragged(first: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The indices first[i] .. first[i] + lengths[i] - 1 of all i, in order."""
    total = int(lengths.sum())
    shift = np.repeat(first - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths) if total else np.zeros(0, np.int64)
    return np.arange(total) + shift


def ended(flat: np.ndarray, bounds: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """The same with ``end_id`` after each text."""
    return np.insert(flat, bounds[1:], end_id).astype("<u4"), bounds + np.arange(len(bounds))


def encoded(batches: Iterator[pa.RecordBatch], path: str, end_id: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Each batch, whose last column is the text, with its ended ids and bounds."""
    encoder = Encoder.shared(path)
    for b in textkit.slices(batches, "_text", textkit.SMALL_SLICE):
        yield b, *ended(*encoder.encode(b.column(b.num_columns - 1)), end_id)


def crc32(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4", copy=False).tobytes())
