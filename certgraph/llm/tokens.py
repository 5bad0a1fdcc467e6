"""Token ids and token counts of whole texts with the worker's own cache of pieces.

A byte-level BPE splitter always breaks before a space that follows a character other than white space, and
what stands on either side of the break does not change what the other side gives. So a text without white
space after a space, and without a trailing space, is the sequence of its space-separated pieces, each with
its space. Pieces are looked up in a cache; those not found are encoded by the tokenizers library, many
joined in one call, and told apart by character offsets. Every other text goes to the library whole.
"""

from __future__ import annotations

import os
import re

import numpy as np

from certgraph.llm.wordhash import BYTE_VALUE, mix, power_table, slices

#: Pieces that a worker's table holds before it starts again.
CACHE_PIECES = 1_500_000
#: Pieces encoded in one string, and text looked up in one set of arrays.
JOINED_PIECES, LOOKUP_BYTES = 96, 1 << 20

_AFTER_SPACE = re.compile(r" \s")
_U2 = np.dtype("<u2")
_rng = np.random.default_rng(881)
_SECOND_VALUE = _rng.integers(0, 2**64, 256, dtype=np.uint64) | np.uint64(1)
_OPENS = np.uint32(0xA5A5F00D)
_coders: dict[tuple[str, bool], tuple[str, PieceCoder | WholeCoder]] = {}


def _load(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.no_padding()
    t.no_truncation()
    return t


def _byte_level(t) -> bool:
    import json

    spec = json.loads(t.to_str())
    pre = spec.get("pre_tokenizer") or {}
    return spec.get("normalizer") is None and pre.get("type") == "ByteLevel" and pre.get("add_prefix_space") is False and pre.get("use_regex") is True and (spec.get("model") or {}).get("type") == "BPE"


class PieceTable:
    """Compact hash table from a piece to its ids or their number; open addressing in numpy arrays.

    A piece is known by two independent hashes of its bytes, of 64 and 32 bits, and by whether it opens a text. At most
    three slots in four are taken.
    """

    def __init__(self, bits: int = 16, with_ids: bool = True, dtype: np.dtype = _U2):
        self.with_ids, self.used = with_ids, 0
        self._alloc(bits)
        self.pool = np.zeros(1 << 16 if with_ids else 0, dtype=dtype)
        self.filled = 0

    def _alloc(self, bits: int) -> None:
        n = 1 << bits
        self.mask = np.uint64(n - 1)
        self.key, self.check = np.zeros(n, dtype=np.uint64), np.zeros(n, dtype=np.uint32)
        self.start, self.size = np.zeros(n if self.with_ids else 0, dtype=np.uint32), np.zeros(n, dtype=np.int32)

    def find(self, key: np.ndarray, check: np.ndarray) -> np.ndarray:
        """Slot of each piece, -1 if it isn't there."""
        slot = (key & self.mask).astype(np.int64)
        out = np.full(len(key), -1, dtype=np.int64)
        here = self.key[slot]
        hit = (here == key) & (self.check[slot] == check)
        out[hit] = slot[hit]
        todo = np.flatnonzero(~hit & (here != 0))
        while len(todo):
            at = (slot[todo] + 1) & int(self.mask)
            slot[todo] = at
            here = self.key[at]
            hit = (here == key[todo]) & (self.check[at] == check[todo])
            out[todo[hit]] = at[hit]
            todo = todo[~hit & (here != 0)]
        return out

    def add(self, key: np.ndarray, check: np.ndarray, sizes: np.ndarray, ids: np.ndarray | None) -> None:
        """Put in pieces that are not there yet, each once; `ids` are theirs, one after the other."""
        while (self.used + len(key)) * 4 > len(self.key) * 3:
            self._grow()
        starts = None
        if self.with_ids:
            while self.filled + len(ids) > len(self.pool):
                self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
            starts = self.filled + np.cumsum(sizes, dtype=np.int64) - sizes
            self.pool[self.filled : self.filled + len(ids)] = ids
            self.filled += len(ids)
        self._place(key, check, sizes, starts)
        self.used += len(key)

    def _place(self, key, check, sizes, starts) -> None:
        todo = np.arange(len(key))
        slot = (key & self.mask).astype(np.int64)
        while len(todo):
            at = slot[todo]
            free = self.key[at] == 0
            first = np.zeros(len(todo), dtype=bool)
            first[np.unique(at, return_index=True)[1]] = True
            put = free & first
            p, q = at[put], todo[put]
            self.key[p], self.check[p], self.size[p] = key[q], check[q], sizes[q]
            if self.with_ids:
                self.start[p] = starts[q]
            todo = todo[~put]
            slot[todo] = (slot[todo] + 1) & int(self.mask)

    def _grow(self) -> None:
        live = np.flatnonzero(self.key)
        old = self.key[live], self.check[live], self.size[live], self.start[live] if self.with_ids else None
        self._alloc(len(self.key).bit_length())
        self._place(*old)


class Pieces:
    """Space-separated pieces of joined texts, with hashes; `opens` marks the first piece of each text."""

    def __init__(self, raws: list[bytes]):
        self.raw = b" ".join(raws) + b" "
        d = np.frombuffer(self.raw, dtype=np.uint8)
        self.ends = np.flatnonzero(d == 0x20)
        self.starts = np.concatenate([[0], self.ends[:-1] + 1])
        up, down = power_table(len(d))
        self.key = self._hash(BYTE_VALUE, d, up, down)
        self.key[self.key == 0] = 1
        self.check = (self._hash(_SECOND_VALUE, d, up, down) >> np.uint64(32)).astype(np.uint32)
        offsets = np.zeros(len(raws) + 1, dtype=np.int64)
        np.cumsum([len(r) + 1 for r in raws], out=offsets[1:])
        self.bounds = np.searchsorted(self.starts, offsets)
        self.opens = np.zeros(len(self.starts), dtype=bool)
        self.opens[self.bounds[:-1]] = True
        self.check[self.opens] ^= _OPENS

    def _hash(self, values, d, up, down) -> np.ndarray:
        sums = np.zeros(len(d) + 1, dtype=np.uint64)
        np.cumsum(values[d] * up[: len(d)], out=sums[1:])
        return mix((sums[self.ends] - sums[self.starts]) * down[self.starts])


class PieceCoder:
    """Encodes texts piece by piece from the worker's table, the missing ones with the tokenizers library."""

    def __init__(self, tokenizer, lengths_only: bool, frequent: PieceTable | None = None):
        self.t = tokenizer
        self.type = np.dtype("<u2") if tokenizer.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        self.lengths_only = lengths_only
        self.frequent = frequent if lengths_only else None
        self.table = PieceTable(with_ids=not lengths_only, dtype=self.type)
        self.marks = [x.content for x in tokenizer.get_added_tokens_decoder().values()]

    def _plain(self, text: str) -> bool:
        return not (text.endswith(" ") or _AFTER_SPACE.search(text) or any(m in text for m in self.marks))

    def encode(self, texts: list[str | None]) -> list:
        """For each text its ids as little-endian bytes of `type`, or their number."""
        out: list = [0 if self.lengths_only else b""] * len(texts)
        plain = [i for i, t in enumerate(texts) if t and self._plain(t)]
        done = set(plain)
        whole = [i for i, t in enumerate(texts) if t and i not in done]
        for k in range(0, len(whole), 64):
            some = whole[k : k + 64]
            for i, e in zip(some, self.t.encode_batch_fast([texts[i] for i in some], add_special_tokens=False), strict=True):
                out[i] = len(e.ids) if self.lengths_only else np.array(e.ids, dtype=self.type).tobytes()
        raws = [texts[i].encode("utf-8") for i in plain]
        for a, b in slices([len(r) for r in raws], LOOKUP_BYTES):
            for i, v in zip(plain[a:b], self._encode_slice(raws[a:b]), strict=True):
                out[i] = v
        return out

    def _encode_slice(self, raws: list[bytes], renewed: bool = False) -> list:
        p = Pieces(raws)
        sizes = np.zeros(len(p.key), dtype=np.int64)
        todo = np.flatnonzero(p.ends > p.starts)
        if self.frequent is not None:
            slot = self.frequent.find(p.key[todo], p.check[todo])
            hit = slot >= 0
            sizes[todo[hit]] = self.frequent.size[slot[hit]]
            todo = todo[~hit]
        slot = self.table.find(p.key[todo], p.check[todo])
        table, miss = self.table, slot < 0
        if miss.any():
            new = todo[miss]
            _, first, back = np.unique(p.key[new] ^ (p.check[new].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)), return_index=True, return_inverse=True)
            one = new[first]
            order, own_sizes, own_ids = self._encode_new(p, one)
            if self.lengths_only:  # before the table grows and slots move
                by_piece = np.empty_like(own_sizes)
                by_piece[order] = own_sizes
                sizes[new] = by_piece[back]
                sizes[todo[~miss]] = table.size[slot[~miss]]
            if self.table.used + len(one) > CACHE_PIECES and not renewed:  # start again, with this slice at least
                self.table = table = PieceTable(with_ids=not self.lengths_only, dtype=self.type)
                self.table.add(p.key[one[order]], p.check[one[order]], own_sizes, own_ids)
                return self._encode_slice(raws, renewed=True)
            self.table.add(p.key[one[order]], p.check[one[order]], own_sizes, own_ids)
            if not self.lengths_only:
                slot = table.find(p.key[todo], p.check[todo])
        elif self.lengths_only:
            sizes[todo] = table.size[slot]
        if self.lengths_only:
            ends = np.concatenate([[0], np.cumsum(sizes)])[p.bounds]
            return np.diff(ends).tolist()
        sizes[todo] = table.size[slot]
        begins = np.zeros(len(sizes), dtype=np.int64)
        begins[todo] = table.start[slot]
        ends = np.cumsum(sizes)
        ids = table.pool[np.repeat(begins - (ends - sizes), sizes) + np.arange(int(ends[-1]) if len(ends) else 0)]
        cuts = np.concatenate([[0], ends])[p.bounds]
        return [ids[a:b].tobytes() for a, b in zip(cuts, cuts[1:], strict=False)]

    def _encode_new(self, p: Pieces, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The pieces in the order in which they were encoded, with their token numbers and all their ids in that order."""
        words = [p.raw[a:b].decode("utf-8") for a, b in zip(p.starts[at].tolist(), p.ends[at].tolist(), strict=True)]
        opens = p.opens[at]
        inner, alone = np.flatnonzero(~opens), np.flatnonzero(opens)
        cut = range(0, len(inner), JOINED_PIECES)
        groups = [[words[i] for i in inner[k : k + JOINED_PIECES].tolist()] for k in cut]
        # a piece that opens a text has no space before it: it is a string of its own
        own = [" " + " ".join(g) for g in groups] + [words[i] for i in alone.tolist()]
        sizes, ids = [], []
        for k, e in enumerate(self.t.encode_batch(own, add_special_tokens=False)):
            found = np.array(e.ids, dtype=self.type)
            ids.append(found)
            if k >= len(groups):
                sizes.append([len(found)])
                continue
            begins = np.cumsum([0, *(len(w) + 1 for w in groups[k])])
            sizes.append(np.diff(np.searchsorted(np.array([o[0] for o in e.offsets]), begins)))
        none = np.zeros(0, dtype=np.int64)
        return np.concatenate([inner, alone]), np.concatenate(sizes) if sizes else none, np.concatenate(ids) if ids else none.astype(self.type)


class WholeCoder:
    """Any other tokenizer file: whole texts through its library."""

    def __init__(self, path: str, lengths_only: bool):
        self.lengths_only = lengths_only
        if path.endswith(".model"):
            import sentencepiece

            self.sp, self.t = sentencepiece.SentencePieceProcessor(model_file=path), None
            size = self.sp.get_piece_size()
        else:
            self.sp, self.t = None, _load(path)
            size = self.t.get_vocab_size()
        self.type = np.dtype("<u2") if size <= 1 << 16 else np.dtype("<u4")

    def encode(self, texts: list[str | None]) -> list:
        out = []
        for k in range(0, len(texts), 64):
            some = [t or "" for t in texts[k : k + 64]]
            ids = self.sp.encode(some, num_threads=1) if self.sp else [e.ids for e in self.t.encode_batch_fast(some, add_special_tokens=False)]
            out += [len(x) if self.lengths_only else np.array(x, dtype=self.type).tobytes() for x in ids]
        return out


def coder(path: str, lengths_only: bool = False, frequent: PieceTable | None = None, frequent_key: str = ""):
    """The worker's coder for a tokenizer file; it lives as long as the worker, or until another table of frequent pieces comes."""
    key = (path, lengths_only)
    known, found = _coders.get(key, (None, None))
    if found is None or known != frequent_key:
        if path.endswith(".model"):
            found = WholeCoder(path, lengths_only)
        else:
            t = _load(path)
            found = PieceCoder(t, lengths_only, frequent) if _byte_level(t) else WholeCoder(path, lengths_only)
        _coders[key] = (frequent_key, found)
    return found
