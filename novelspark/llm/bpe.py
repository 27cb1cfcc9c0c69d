"""Byte-pair encoding shared by the token operators.

``UnitEncoder`` gives exactly the ids of the ``tokenizers`` library for the byte-level BPE file, but encodes every distinct
*unit* of a batch once.  A unit is a blank before a non-space character with all that follows up to the next such blank.
The byte-level splitting rule always starts a new piece at such a blank, so units can be encoded apart.  Fresh units of
everyday characters are encoded in one call of ``tiktoken`` over the same vocabulary (its ranks); units with other
characters or with a special token's string go to ``tokenizers``.  Both give the same ids, which a test compares.

Memory is bounded: the unit table is emptied once it holds ``max_units`` units, and a call works through its texts in lots of
``LOT_CHARS`` characters (a longer text is a lot of its own).
"""

from __future__ import annotations

import os
import re

import numpy as np

DEFAULT_FILE = "byte_bpe_50k.json"
RANK_FILES = {"byte_bpe_50k.json": "byte_bpe_50k.tiktoken"}
SPECIAL = "<|endoftext|>"
LOT_CHARS = 2_000_000
CUT = re.compile(r" (?=\S)")
UNEVEN = re.compile(r" (?:\s|\Z)")
RARE = re.compile("[^\x20-\x7e\n\t\r\u00a1-\u024f]")


def tokenizer_path(name: str = DEFAULT_FILE) -> str:
    """Place of a vocabulary file of the ``public_tokenizers`` package."""
    import public_tokenizers

    return public_tokenizers.path(name)


def rank_encoder(path: str):
    """The ``tiktoken`` encoder over the same vocabulary as the file at ``path``, or None where there is none."""
    import base64

    import public_tokenizers
    import tiktoken

    ranks = RANK_FILES.get(os.path.basename(path))
    if ranks is None:
        return None
    with open(public_tokenizers.path(ranks), "rb") as lines:
        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("units", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})._core_bpe


def token_bytes(tokenizer) -> tuple[np.ndarray, np.ndarray]:
    """Sizes and joined bytes of all tokens of a byte-level vocabulary."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(printable)]
    byte_of = {chr(b): b for b in printable} | {chr(256 + k): b for k, b in enumerate(rest)}
    added = set(tokenizer.get_added_tokens_decoder())
    each = []
    for i in range(tokenizer.get_vocab_size(with_added_tokens=True)):
        token = tokenizer.id_to_token(i) or ""
        each.append(token.encode() if i in added else bytes(byte_of[c] for c in token))
    return np.fromiter(map(len, each), dtype=np.int64, count=len(each)), np.frombuffer(b"".join(each), dtype=np.uint8)


def lots(texts: list[str | None], chars: int = LOT_CHARS):
    """The texts in order, in lists of bounded length in characters."""
    lot, held = [], 0
    for t in texts:
        size = len(t or "")
        if lot and held + size > chars:
            yield lot
            lot, held = [], 0
        lot.append(t)
        held += size
    if lot:
        yield lot


class UnitEncoder:
    def __init__(self, path: str | None = None, max_units: int = 250_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        path = path or tokenizer_path()
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.ranks = rank_encoder(path)
        self.token_sizes, _ = token_bytes(self.tokenizer)
        self.max_units = max_units
        self._reset()

    def _reset(self) -> None:
        self.known: dict[str, int] = {}
        self.starts = np.zeros(1024, dtype=np.int64)
        self.sizes = np.zeros(1024, dtype=np.int64)
        self.pool = np.zeros(8192, dtype=np.uint32)
        self.filled = 0

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        """Ids by the library itself."""
        return [np.array(e.ids, dtype=np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _add(self, units: list[str], sizes: np.ndarray, flat: np.ndarray) -> None:
        first = len(self.known)
        while len(self.pool) < self.filled + len(flat):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        while len(self.starts) < first + len(units):
            self.starts = np.concatenate([self.starts, np.zeros_like(self.starts)])
            self.sizes = np.concatenate([self.sizes, np.zeros_like(self.sizes)])
        self.pool[self.filled : self.filled + len(flat)] = flat
        self.sizes[first : first + len(units)] = sizes
        self.starts[first : first + len(units)] = self.filled + np.cumsum(sizes) - sizes
        self.filled += len(flat)
        self.known.update(zip(units, range(first, first + len(units)), strict=True))

    def _numbers(self, units: list[str]) -> list[int]:
        """Place of each of these different units in the table; unknown ones are encoded and added."""
        known = self.known
        fresh = [u for u in units if u not in known]
        if len(known) + len(fresh) > self.max_units:
            self._reset()
            known, fresh = self.known, units
        if fresh:
            joint, apart = [], []
            for k in range(0, len(fresh), 2048):
                block = fresh[k : k + 2048]
                text = "".join(block)
                if self.ranks and not RARE.search(text) and SPECIAL not in text and "  " not in text and all(u[0] == " " for u in block):
                    joint += block
                    continue
                for u in block:
                    (joint if self.ranks and u[0] == " " and u[1:2] not in ("", " ") and not RARE.search(u) and SPECIAL not in u else apart).append(u)
            if joint:
                flat = np.frombuffer(self.ranks.encode_to_tiktoken_buffer("".join(joint), set()), dtype=np.uint32)
                ends = np.cumsum(np.fromiter(map(len, map(str.encode, joint)), dtype=np.int64, count=len(joint)))
                last = np.searchsorted(np.cumsum(self.token_sizes[flat]), ends)  # the token in which each unit ends
                self._add(joint, np.diff(last, prepend=-1), flat)
            if apart:
                ids = self.whole(apart)
                self._add(apart, np.fromiter(map(len, ids), dtype=np.int64, count=len(ids)), np.concatenate(ids))
        return list(map(known.__getitem__, units))

    def _places(self, values, head: np.ndarray) -> np.ndarray:
        """Table place of each unit, -1 for empty ones; ``head`` marks the first unit of a text, before which no blank stands."""
        import pyarrow.compute as pc

        coded = pc.dictionary_encode(values)
        codes = coded.indices.to_numpy()
        words = coded.dictionary.to_pylist()
        used = np.zeros(len(words), dtype=bool)
        used[codes[~head]] = True
        inner = np.flatnonzero(used)
        firsts = [words[c] for c in codes[head].tolist()]
        names = [" " + words[i] for i in inner.tolist()]
        all_names = list(dict.fromkeys(names + [w for w in firsts if w]))
        number = dict(zip(all_names, self._numbers(all_names), strict=True))
        places = np.full(len(words), -1, dtype=np.int64)
        places[inner] = np.fromiter(map(number.__getitem__, names), dtype=np.int64, count=len(names))
        out = places[codes]
        out[head] = np.fromiter((number.get(w, -1) for w in firsts), dtype=np.int64, count=len(firsts))
        return out

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        """Ids of each text as unsigned 32-bit arrays; a null text counts as empty."""
        out: list[np.ndarray] = []
        for lot in lots(texts):
            out += self._encode(lot)
        return out

    def _encode(self, texts: list[str | None]) -> list[np.ndarray]:
        import pyarrow as pa
        import pyarrow.compute as pc

        texts = [t or "" for t in texts]
        uneven = [k for k, t in enumerate(texts) if UNEVEN.search(t)]
        even = texts
        if uneven:
            odd = set(uneven)
            even = [t for k, t in enumerate(texts) if k not in odd]
        order = [k for k in range(len(texts)) if k not in odd] + uneven if uneven else range(len(texts))
        parts = pc.split_pattern(pa.array(even, type=pa.large_string()), " ")
        values, counts = parts.flatten(), np.diff(parts.offsets.to_numpy())
        if uneven:
            cut = [CUT.split(texts[k]) for k in uneven]
            counts = np.concatenate([counts, np.fromiter(map(len, cut), dtype=np.int64, count=len(cut))])
            values = pa.concat_arrays([values, pa.array([u for c in cut for u in c], type=pa.large_string())])
        if not len(values):
            return [np.zeros(0, dtype=np.uint32) for _ in texts]
        head = np.zeros(len(values), dtype=bool)
        head[(np.cumsum(counts) - counts)[counts > 0]] = True
        places = self._places(values, head)
        sizes = np.where(places < 0, 0, self.sizes[places])
        starts = np.where(places < 0, 0, self.starts[places])
        ends = np.cumsum(sizes)
        flat = self.pool[np.repeat(starts - (ends - sizes), sizes) + np.arange(ends[-1])]
        bounds = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(counts)])]
        out: list[np.ndarray] = [flat[:0]] * len(texts)
        for k, i in enumerate(order):
            out[i] = flat[bounds[k] : bounds[k + 1]]
        return out

    def count(self, texts: list[str | None]) -> np.ndarray:
        """Number of ids of each text."""
        return np.fromiter((len(x) for lot in lots(texts) for x in self._encode(lot)), dtype=np.int64, count=len(texts))


class ByteDecoder:
    """Bytes of ids, as the library's byte-level decoder gives them."""

    def __init__(self, tokenizer):
        self.sizes, self.pool = token_bytes(tokenizer)
        self.starts = np.cumsum(self.sizes) - self.sizes

    def decode(self, ids: np.ndarray) -> str:
        sizes, starts = self.sizes[ids], self.starts[ids]
        ends = np.cumsum(sizes)
        if not len(ends):
            return ""
        index = np.repeat(starts - (ends - sizes), sizes) + np.arange(ends[-1])
        return self.pool[index].tobytes().decode("utf-8", errors="replace")


_held: dict[tuple, UnitEncoder] = {}


def encoder(path: str | None = None) -> UnitEncoder:
    """One encoder per Python worker and vocabulary file."""
    key = (path,)
    if key not in _held:
        _held[key] = UnitEncoder(path)
    return _held[key]
