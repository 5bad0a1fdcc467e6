"""A hidden Markov language model of word sequences, and the add-one unigram baseline beside it.

Words are tokens; every text ends with one end token. The model's latent states emit classes of words: each frequent word
is a class of its own (at most 1 / HEAD_SHARE of them), other words fall into classes by their last bytes, words seen
once in training into like classes of their own, and unseen words form one class. A class gives its words by their
training counts, the class of unseen words each of them by one share of an estimated number of unseen types, which are taken to
be as many as the types seen once. So all tables
that the workers need are of bounded size while counts cover every word; the grain of the classes is a share of the corpus,
thus as the corpus grows more words (though no greater share of tokens) are told apart by their endings only.

Counting. Texts are cut into blocks of bounded size. A block's distinct words are cut by hash into 256 ranges, and the like
ranges of 256 neighbouring blocks are summed; these sums are cut and summed in the same way, until one group holds all
blocks. Totals go back down the same way. A level moves 256 rows for each block, so rows grow with n log n, and no group
holds more than 256 such pieces, some kilobytes each. Training is Baum-Welch: a start from a bounded sample, then passes over all training
texts, in which every task adds up expected counts and the sums are merged in a tree. The score is the exact likelihood by
the scaled forward recursion over the whole text, in stretches of bounded size.

Words are compared by 64-bit hashes.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.llm.wordhash import Words, mix, slices, text_bytes
from certgraph.operators.edges import dense_numbers
from certgraph.plans.staging import Stages

#: A word with at least this share of all training tokens is a class of its own.
HEAD_SHARE = 2e-5
TAIL_CLASSES, STATES = 4096, 8
#: Texts of the starting sample, its rounds, and passes over all training texts.
SAMPLE_TEXTS, SAMPLE_ROUNDS, FULL_PASSES = 512, 12, 2
#: Text of one counting block, and tokens whose forward and backward values are held at a time.
BLOCK_BYTES, HELD_TOKENS = 12 << 20, 250_000
FAN_IN = 16
#: Two to the power of this: how many blocks' words are summed in one step, and hash ranges that each sum is cut into.
FAN_BITS = 8


def _squeeze(a: np.ndarray) -> bytes:
    """Array bytes by place value, compressed."""
    import zstandard

    planes = np.ascontiguousarray(a).view(np.uint8).reshape(-1, a.dtype.itemsize).T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(planes).tobytes())


def _widen(raw: bytes, dtype) -> np.ndarray:
    import zstandard

    d = np.dtype(dtype)
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), dtype=np.uint8)
    return np.ascontiguousarray(planes.reshape(d.itemsize, -1).T).view(d).reshape(-1)


def held_out(doc_id) -> bool:
    """Texts whose id, as text, has remainder 2 by 7 in its CRC are not learned from; a missing id is learned from."""
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 7 == 2


def _tails(w: Words) -> np.ndarray:
    """Class of each word by its last three bytes."""
    d = w.data.astype(np.uint64)
    x = d[w.ends - 1] + np.uint64(1)
    for back in (2, 3):
        at = w.ends - back
        x = x * np.uint64(257) + np.where(at >= w.starts, d[np.maximum(at, 0)] + np.uint64(1), np.uint64(0))
    return (mix(x) % np.uint64(TAIL_CLASSES)).astype(np.uint16)


_BLOCK_FIELDS = pa.schema([("block", pa.int64()), ("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("words", pa.binary()), ("hashes", pa.binary()), ("tails", pa.binary()), ("counts", pa.binary())])
_BLOCK_DDL = "block long, doc_id long, held_out boolean, n_tokens long, words binary, hashes binary, tails binary, counts binary"


def _blocks(block_bytes: int):
    """Texts to rows with their words numbered within the block, then one row with the block's distinct words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _into_blocks(batches, block_bytes)

    return run


def _into_blocks(batches: Iterator[pa.RecordBatch], block_bytes: int) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext

    part, number = TaskContext.get().partitionId(), 0
    held: list[tuple] = []  # ids, hashes, tails of a slice, word bounds
    size = 0

    def flush():
        hashes = np.concatenate([h for _, h, _, _ in held])
        distinct, first, back = np.unique(hashes, return_index=True, return_inverse=True)
        tails = np.concatenate([t for _, _, t, _ in held])[first]
        counts = np.zeros(len(distinct), dtype=np.int64)
        block, at, rows = (part << 24) + number, 0, []
        back = back.astype("<u4")
        for ids, h, _, bounds in held:
            for k, doc in enumerate(ids):
                own = back[at + bounds[k] : at + bounds[k + 1]]
                out = held_out(doc)
                if not out:
                    counts += np.bincount(own, minlength=len(distinct)) if len(own) > len(distinct) // 8 else 0
                    if len(own) <= len(distinct) // 8:
                        np.add.at(counts, own, 1)
                rows.append({"block": block, "doc_id": doc, "held_out": out, "n_tokens": len(own) + 1, "words": _squeeze(own)})
            at += len(h)
        rows.append({"block": block, "hashes": distinct.astype("<u8").tobytes(), "tails": tails.astype("<u2").tobytes(), "counts": _squeeze(counts.astype("<i8"))})
        for k in range(0, len(rows), 2000):
            yield pa.RecordBatch.from_pylist(rows[k : k + 2000], schema=_BLOCK_FIELDS)

    for batch in batches:
        for k in range(0, batch.num_rows, 1000):
            some = batch.slice(k, 1000)
            ids, raws = some.column(0).to_pylist(), [text_bytes(t, lower=True) for t in some.column(1).to_pylist()]
            for a, b in slices([len(r) for r in raws]):
                w = Words(raws[a:b])
                held.append((ids[a:b], w.hashes, _tails(w), w.bounds - w.bounds[0]))
                size += len(w.data)
                if size >= block_bytes:
                    yield from flush()
                    held, size, number = [], 0, number + 1
    if held:
        yield from flush()


_PIECE = pa.schema([("g", pa.int64()), ("p", pa.int64()), ("child", pa.int64()), ("hashes", pa.binary()), ("tails", pa.binary()), ("counts", pa.binary())])
_PIECE_DDL = "g long, p long, child long, hashes binary, tails binary, counts binary"
_SUM_DDL = "g long, p long, hashes binary, tails binary, counts binary"
_TOTAL = pa.schema([("g", pa.int64()), ("p", pa.int64()), ("part", pa.int64()), ("totals", pa.binary()), ("tails", pa.binary()), ("heads", pa.binary())])
_TOTAL_DDL = "g long, p long, part long, totals binary, tails binary, heads binary"


def _cut(level: int, bits: int):
    """Each holder's words, cut by the bits of the hash that follow those of its own range."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fan, shift = 1 << bits, np.uint64(64 - bits * (level + 1))
        for batch in batches:
            for r in batch.to_pylist():
                h, t, c = np.frombuffer(r["hashes"], "<u8"), np.frombuffer(r["tails"], "<u2"), _widen(r["counts"], "<i8")
                cuts = np.searchsorted((h >> shift) & np.uint64(fan - 1), np.arange(fan + 1, dtype=np.uint64))
                rows = [{"g": r["g"] // fan, "p": r["p"] * fan + i, "child": r["g"], "hashes": h[a:b].tobytes(), "tails": t[a:b].tobytes(), "counts": _squeeze(c[a:b])} for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if b > a]
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=_PIECE)

    return run


def _merged(table: pa.Table) -> tuple[list[dict], list[np.ndarray], np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Pieces of one range and group, in order of their holders: rows, their words, and sums by distinct word."""
    rows = sorted(table.to_pylist(), key=lambda r: r["child"])
    hs = [np.frombuffer(r["hashes"], "<u8") for r in rows]
    distinct, first, back = np.unique(np.concatenate(hs), return_index=True, return_inverse=True)
    total = np.bincount(back, weights=np.concatenate([_widen(r["counts"], "<i8") for r in rows]), minlength=len(distinct)).astype("<i8")
    tails = np.concatenate([np.frombuffer(r["tails"], "<u2") for r in rows])[first]
    return rows, hs, distinct, back, total, tails


def _summed(table: pa.Table) -> pa.Table:
    rows, _, distinct, _, total, tails = _merged(table)
    out = [{"g": rows[0]["g"], "p": rows[0]["p"], "hashes": distinct.tobytes(), "tails": tails.astype("<u2").tobytes(), "counts": _squeeze(total)}]
    return pa.Table.from_pylist(out, schema=pa.schema([f for f in _PIECE if f.name != "child"]))


def _pieces_back(bits: int, rows: list[dict], hs: list[np.ndarray], back: np.ndarray, total: np.ndarray, tails: np.ndarray, heads: np.ndarray) -> list[dict]:
    """Totals of a range for each holder that gave a piece; a holder's own range is its p without the last digit."""
    out, at = [], 0
    for r, h in zip(rows, hs, strict=True):
        own = back[at : at + len(h)]
        out.append({"g": r["child"], "p": r["p"] >> bits, "part": r["p"] & ((1 << bits) - 1), "totals": _squeeze(total[own]), "tails": _squeeze(tails[own]), "heads": _squeeze(heads[own])})
        at += len(h)
    return out


def _totals(head_least: float, bits: int):
    """Totals of one range over all blocks; a row for each holder below, and one with what the whole range holds."""

    def run(table: pa.Table) -> pa.Table:
        rows, hs, distinct, back, total, tails = _merged(table)
        head = total >= head_least
        once = (total == 1) & ~head
        sums = np.concatenate([np.bincount(tails[m], weights=total[m], minlength=TAIL_CLASSES) for m in ((total > 1) & ~head, once)])
        out = _pieces_back(bits, rows, hs, back, total, tails, np.where(head, distinct, 0).astype("<u8"))
        seen = np.array([(total > 0).sum(), once.sum()], dtype="<i8")
        out.append({"g": None, "p": rows[0]["p"], "part": None, "totals": _squeeze(seen), "tails": sums.astype("<f8").tobytes(), "heads": np.stack([distinct[head], total[head].astype(np.uint64)]).astype("<u8").tobytes()})
        return pa.Table.from_pylist(out, schema=_TOTAL)

    return run


def _handed_down(bits: int):
    """Totals of a holder, in pieces by the next digit of the hash, to the holders whose words it sums."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return _TOTAL.empty_table()
        rows, hs, _, back, _, _ = _merged(left)
        parts = sorted(right.to_pylist(), key=lambda r: r["part"])
        totals, tails, heads = (np.concatenate([_widen(r[c], d) for r in parts]) for c, d in (("totals", "<i8"), ("tails", "<u2"), ("heads", "<u8")))
        return pa.Table.from_pylist(_pieces_back(bits, rows, hs, back, totals, tails, heads), schema=_TOTAL)

    return run


def _word_totals(st: Stages, words: DataFrame, head_least: float, bits: int) -> tuple[DataFrame, DataFrame]:
    """(g = block, part, totals, tails, heads) for each block, and a row for each hash range over all blocks."""
    holders, levels = words, []
    for level in range(64 // bits):
        pieces = st.keep(holders.mapInArrow(_cut(level, bits), _PIECE_DDL), "pieces")
        levels.append(pieces)
        if (pieces.agg(F.max("g")).first()[0] or 0) == 0:
            break
        holders = st.keep(pieces.groupBy("g", "p").applyInArrow(_summed, _SUM_DDL), "sums")
    found = st.keep(levels[-1].groupBy("g", "p").applyInArrow(_totals(head_least, bits), _TOTAL_DDL), "totals")
    whole, down = found.filter("g IS NULL"), found.filter("g IS NOT NULL")
    for pieces in reversed(levels[:-1]):
        down = st.keep(pieces.groupBy("g", "p").cogroup(down.groupBy("g", "p")).applyInArrow(_handed_down(bits), _TOTAL_DDL), "totals")
    st.drop(*levels)
    return down, whole


def _tree_sum(st: Stages, rows: DataFrame, dtype: str = "<f8") -> np.ndarray | None:
    """Sum of equally long float arrays in (part long, blob binary), merged FAN_IN rows at a time."""

    def merge(table: pa.Table) -> pa.Table:
        total = None
        for raw in table.column("blob").to_pylist():
            a = np.frombuffer(raw, dtype)
            total = a.copy() if total is None else total + a
        return pa.table({"part": pa.array([table.column("part")[0].as_py() // FAN_IN], pa.int64()), "blob": pa.array([total.tobytes()], pa.binary())})

    rows = st.keep(rows, "partial")
    while (n := rows.count()) > 1:
        least = rows.agg(F.min("part"), F.max("part")).first()
        span = F.floor(F.col("part") / F.lit(FAN_IN)) if least[1] // FAN_IN > least[0] // FAN_IN or n <= FAN_IN else F.col("part") % F.lit(max(1, n // FAN_IN))
        nxt = st.keep(rows.groupBy(span.alias("g")).applyInArrow(merge, "part long, blob binary"), "partial")
        st.drop(rows)
        rows = nxt
    got = rows.first()
    return None if got is None else np.frombuffer(got.blob, dtype)


@dataclass
class Vocabulary:
    """What workers need to know of the words: bounded by HEAD_SHARE and TAIL_CLASSES."""

    tokens: int  # N
    types: int  # V
    ends: int
    heads: np.ndarray  # sorted hashes
    head_counts: np.ndarray
    tail_sums: np.ndarray  # words seen more than once, then those seen once, by class
    once: int = 0  # types seen once

    @property
    def new_types(self) -> float:
        """Types that training missed: taken to be as many as it saw once, which all together are as likely as new ones."""
        return max(1.0, float(self.once))

    @property
    def classes(self) -> int:
        return len(self.heads) + 2 * TAIL_CLASSES + 2

    @property
    def unseen(self) -> int:
        return self.classes - 2

    @property
    def end(self) -> int:
        return self.classes - 1

    def shares(self) -> np.ndarray:
        """Training tokens of each class."""
        return np.concatenate([self.head_counts, self.tail_sums, [0, self.ends]]).astype(float)


def _encoded(v: Vocabulary):
    """A block's texts with the totals of its words, to classes and the parts of the scores that need no states."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        rows = sorted(right.to_pylist(), key=lambda r: r["part"])
        if rows:
            c = np.concatenate([_widen(r["totals"], "<i8") for r in rows])
            tails = np.concatenate([_widen(r["tails"], "<u2") for r in rows]).astype(np.int64)
            heads = np.concatenate([_widen(r["heads"], "<u8") for r in rows])
        else:
            c, tails, heads = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
        h = len(v.heads)
        place = h + np.where(c == 1, TAIL_CLASSES, 0) + tails
        is_head = heads != 0
        place[is_head] = np.searchsorted(v.heads, heads[is_head])
        place[c == 0] = v.unseen
        inner = np.zeros(len(c))
        plain = (c > 0) & ~is_head
        inner[plain] = np.log(c[plain] / v.tail_sums[place[plain] - h])
        inner[c == 0] = -np.log(v.new_types)
        base = np.log10((c + 1) / (v.tokens + v.types + 1))
        base_end = np.log10((v.ends + 1) / (v.tokens + v.types + 1))
        out: dict[str, list] = {k: [] for k in ("doc_id", "held_out", "n_tokens", "n_known", "base_score", "inner", "classes")}
        for batch in left.to_batches():
            for doc, held, n, words in zip(*(batch.column(x).to_pylist() for x in ("doc_id", "held_out", "n_tokens", "words")), strict=True):
                own = _widen(words, "<u4")
                out["doc_id"].append(doc)
                out["held_out"].append(held)
                out["n_tokens"].append(n)
                out["n_known"].append(int((c[own] > 0).sum()) + (v.ends > 0))
                out["base_score"].append(float(base[own].sum() + base_end))
                out["inner"].append(float(inner[own].sum()))
                out["classes"].append(_squeeze(place[own].astype("<u2")))
        kinds = {"doc_id": pa.int64(), "held_out": pa.bool_(), "n_tokens": pa.int64(), "n_known": pa.int64(), "base_score": pa.float64(), "inner": pa.float64(), "classes": pa.binary()}
        return pa.table({k: pa.array(x, kinds[k]) for k, x in out.items()})

    return run


# ------------------------------------------------------------------------------------------------ the model


@dataclass
class HiddenMarkov:
    first: np.ndarray  # states
    move: np.ndarray  # states x states
    emit: np.ndarray  # classes x states

    def _walk(self, texts: list[np.ndarray]):
        """Tokens of the texts laid out by time, longest text first: order, active texts by time, begin of each time."""
        if len(texts) == 1:
            n = len(texts[0])
            return np.zeros(1, dtype=np.int64), np.ones(n, dtype=np.int64), np.arange(n + 1), texts[0]
        order = np.argsort([-len(t) for t in texts], kind="stable")
        lengths = np.array([len(texts[i]) for i in order])
        active = len(lengths) - np.searchsorted(lengths[::-1], np.arange(1, lengths[0] + 1))
        begin = np.concatenate([[0], np.cumsum(active)])
        row = np.repeat(np.arange(len(lengths)), lengths)
        time = np.arange(len(row)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
        flat = np.empty(len(row), dtype=np.int64)
        flat[begin[time] + row] = np.concatenate([texts[i] for i in order])
        return order, active, begin, flat

    @staticmethod
    def _stretches(active: np.ndarray, begin: np.ndarray) -> Iterator[tuple[int, int]]:
        """Ranges of times that hold HELD_TOKENS tokens or a single time."""
        s = 0
        while s < len(active):
            t = max(s + 1, int(np.searchsorted(begin, begin[s] + HELD_TOKENS, "right")) - 1)
            yield s, t
            s = t

    def _forward(self, active, begin, flat, s: int, t: int, last):
        """Emissions, forward values and scales of times s to t; `last` holds the forward values of the time before."""
        e = self.emit[flat[begin[s] : begin[t]]]
        alpha, scale = np.empty_like(e), np.empty(len(e))
        for i in range(s, t):
            a, b = begin[i] - begin[s], begin[i + 1] - begin[s]
            f = (self.first if last is None else last[: active[i]] @ self.move) * e[a:b]
            scale[a:b] = f.sum(axis=1)
            alpha[a:b] = f / scale[a:b, None]
            last = alpha[a:b]
        return e, alpha, scale

    def log_likelihoods(self, texts: list[np.ndarray]) -> np.ndarray:
        """Natural logarithm of each text's probability, over all paths."""
        order, active, begin, flat = self._walk(texts)
        sums, last = np.zeros(len(texts)), None
        for s, t in self._stretches(active, begin):
            _, alpha, scale = self._forward(active, begin, flat, s, t, last)
            last = alpha[len(alpha) - active[t - 1] :].copy()
            row = np.arange(len(scale)) - np.repeat(begin[s:t] - begin[s], active[s:t])
            sums += np.bincount(row, weights=np.log(scale), minlength=len(texts))
        out = np.zeros(len(texts))
        out[order] = sums
        return out

    def expected(self, texts: list[np.ndarray]) -> np.ndarray:
        """Expected counts of first states, moves and emissions, in one array."""
        _, active, begin, flat = self._walk(texts)
        k = len(self.first)
        spans, before, last = list(self._stretches(active, begin)), [], None
        for s, t in spans:
            before.append(last)
            e, alpha, scale = self._forward(active, begin, flat, s, t, last)
            last = alpha[len(alpha) - active[t - 1] :].copy()
        moves, emissions, beta = np.zeros((k, k)), np.zeros_like(self.emit), np.ones((active[-1], k))
        for (s, t), last in zip(reversed(spans), reversed(before), strict=True):
            if t < len(active):  # a stretch before the last one is walked again
                e, alpha, scale = self._forward(active, begin, flat, s, t, last)
            lo, gamma = begin[s], np.empty_like(alpha)
            for i in range(t - 1, s - 1, -1):
                a, b = begin[i] - lo, begin[i + 1] - lo
                gamma[a:b] = alpha[a:b] * beta
                if i:
                    ahead = last[: active[i]] if i == s else alpha[begin[i - 1] - lo : begin[i - 1] - lo + active[i]]
                    onward = e[a:b] * beta / scale[a:b, None]
                    moves += ahead.T @ onward
                    beta = np.ones((active[i - 1], k))
                    beta[: active[i]] = onward @ self.move.T
            for j in range(k):
                emissions[:, j] += np.bincount(flat[lo : begin[t]], weights=gamma[:, j], minlength=len(self.emit))
        return np.concatenate([gamma[: active[0]].sum(axis=0), (moves * self.move).ravel(), emissions.ravel()])

    @staticmethod
    def from_counts(counts: np.ndarray, v: Vocabulary, states: int) -> HiddenMarkov:
        """Smoothed probabilities; all unseen words together get, in each state, the share of words seen once."""
        first, move, emit = counts[:states], counts[states : states * (states + 1)].reshape(states, states), counts[states * (states + 1) :].reshape(-1, states)
        share = v.shares() + 0.01
        share /= share.sum()
        emit = (emit + 200.0 * share[:, None]) / (emit.sum(axis=0) + 200.0)
        emit[v.unseen] = 0.0
        h = len(v.heads)
        new = np.maximum(emit[h + TAIL_CLASSES : h + 2 * TAIL_CLASSES].sum(axis=0), 1.0 / (v.tokens + v.types + 1))
        emit[v.unseen] = new
        emit /= emit.sum(axis=0)
        move = (move + 0.1) / (move + 0.1).sum(axis=1, keepdims=True)
        first = (first + 0.1) / (first + 0.1).sum()
        return HiddenMarkov(first, move, emit)


def _groups(texts: list[np.ndarray]) -> Iterator[list[int]]:
    """Texts of like length together, HELD_TOKENS at a time."""
    held, size = [], 0
    for i in np.argsort([len(t) for t in texts], kind="stable"):
        if held and size + len(texts[i]) > HELD_TOKENS:
            yield held
            held, size = [], 0
        held.append(int(i))
        size += len(texts[i])
    if held:
        yield held


def _texts(column: pa.Array, end: int) -> list[np.ndarray]:
    return [np.append(_widen(x, "<u2").astype(np.int64), end) for x in column.to_pylist()]


def _start(texts: list[np.ndarray], v: Vocabulary, states: int) -> HiddenMarkov:
    """A model from the sample: whole texts are dealt to states, then a few Baum-Welch rounds."""
    rng = np.random.default_rng(4)
    emit = np.zeros((v.classes, states))
    for t in texts:
        np.add.at(emit[:, int(rng.integers(states))], t, 1.0)
    sticky = np.eye(states) * 1000.0 + 1.0
    model = HiddenMarkov.from_counts(np.concatenate([np.ones(states), sticky.ravel(), emit.ravel()]), v, states)
    for _ in range(SAMPLE_ROUNDS if texts else 0):
        model = HiddenMarkov.from_counts(sum(model.expected([texts[i] for i in g]) for g in _groups(texts)), v, states)
    return model


def _expectation(model, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        total, m = None, model.value
        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                texts = _texts(batch.column(0).slice(a, 4096), end)
                for g in _groups(texts):
                    x = m.expected([texts[i] for i in g])
                    total = x if total is None else total + x
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([total.tobytes()], pa.binary())], names=["part", "blob"])

    return run


def _scored(model, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for batch in batches:
            logs = np.zeros(batch.num_rows)
            for a in range(0, batch.num_rows, 4096):
                texts = _texts(batch.column(6).slice(a, 4096), end)
                for g in _groups(texts):
                    logs[[a + i for i in g]] = m.log_likelihoods([texts[i] for i in g])
            score = (logs + batch.column(5).to_numpy(zero_copy_only=False)) / np.log(10)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(5)), pa.array(score, pa.float64())], names=["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score"])

    return run


def language_model_scores(docs: DataFrame, states: int = STATES, passes: int = FULL_PASSES, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES, fan_bits: int = FAN_BITS) -> DataFrame:
    """Return doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, one row for each row of `docs`.

    base_score is the add-one unigram log10 probability, with one type for all unseen words; score the hidden Markov model's,
    in which an unseen word costs what its class costs in the path's states and a choice among `Vocabulary.new_types`. HEAD_SHARE and
    TAIL_CLASSES set which words have emissions of their own and which share them by their endings. A null or empty text is its end token alone. Null ids are learned from; repeated ids are
    rows like any other; an empty table gives an empty result; other columns are not read.
    """
    spark = docs.sparkSession
    st = Stages(spark, "hmm")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = st.keep(texts.mapInArrow(_blocks(block_bytes), _BLOCK_DDL), "blocks")
    documents, words = rows.filter("hashes IS NULL"), rows.filter("hashes IS NOT NULL").select("block", "hashes", "tails", "counts")
    learned = documents.filter("NOT held_out").agg(F.sum("n_tokens"), F.count(F.lit(1))).first()
    tokens, ends = int(learned[0] or 0), int(learned[1])
    # blocks are numbered 0, 1, ... so that neighbours form groups
    numbers = st.keep(dense_numbers(words.select("block"), ["block"], "g", first=0), "numbers")
    holders = words.join(numbers, "block").select("g", F.lit(0).cast("long").alias("p"), "hashes", "tails", "counts")
    totals, whole = _word_totals(st, holders, max(2.0, HEAD_SHARE * tokens), fan_bits)

    # 1 / HEAD_SHARE words at most, over all ranges
    heads = [np.frombuffer(x, "<u8").reshape(2, -1) for x in whole.filter(F.octet_length("heads") > 0).select("heads").toArrow().column(0).to_pylist()]
    heads = np.concatenate(heads, axis=1) if heads else np.zeros((2, 0), dtype="<u8")
    by_hash = np.argsort(heads[0])
    sums = _tree_sum(st, whole.select(F.col("p").alias("part"), F.col("tails").alias("blob")))
    seen = _tree_sum(st, whole.select(F.col("p").alias("part"), "totals").mapInArrow(_as_floats, "part long, blob binary"))
    types, once = (int(x) for x in (seen if seen is not None else (0, 0)))
    v = Vocabulary(tokens, types + (ends > 0), ends, heads[0][by_hash], heads[1][by_hash].astype(np.int64), sums if sums is not None else np.zeros(2 * TAIL_CLASSES), once)

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, inner double, classes binary"
    left = documents.select("block", "doc_id", "held_out", "n_tokens", "words")
    right = totals.join(numbers, "g").select("block", "part", "totals", "tails", "heads")
    coded = st.keep(left.groupBy("block").cogroup(right.groupBy("block")).applyInArrow(_encoded(v), schema), "coded")
    st.drop(rows, numbers, totals)

    training = coded.filter("NOT held_out")
    sample = training.orderBy(F.xxhash64("doc_id", "n_tokens", "base_score")).limit(SAMPLE_TEXTS).select("classes").toArrow()
    model = _start([t for b in sample.to_batches() for t in _texts(b.column(0), v.end)], v, states)
    for _ in range(passes):
        shared = spark.sparkContext.broadcast(model)
        counts = _tree_sum(st, training.select("classes").mapInArrow(_expectation(shared, v.end), "part long, blob binary"))
        if counts is None:
            break
        model = HiddenMarkov.from_counts(counts, v, states)
    shared = spark.sparkContext.broadcast(model)
    scored = coded.mapInArrow(_scored(shared, v.end), "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(tokens).cast("long").alias("train_tokens"), "base_score", "score")


def _as_floats(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        blobs = [_widen(x, "<i8").astype("<f8").tobytes() for x in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(blobs, pa.binary())], names=["part", "blob"])
