"""Quality rules: word and repetition counts, and compression bands.

Text that a general-purpose compressor shrinks far more than prose of its length repeats itself; text that it
hardly shrinks is noise, encoded data or a random string. How far prose shrinks depends on its length, so each
length class has limits of its own: general ones, or ones fitted on all texts that are labelled good. The ratio is taken over the whole document and over fixed chunks up to its
last byte, so that a long bad passage in a longer good text counts too, wherever it stands.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certgraph.functions.worker_memory import giving_back
from certgraph.llm.wordhash import Words, slices, text_bytes, window_hashes


@dataclass(frozen=True)
class CompressionBands:
    """Limits of raw size divided by compressed size, by raw size in bytes.

    `limits` holds (size below which the row applies, least ratio, largest ratio), sizes ascending. Frame headers
    alone outweigh any gain on very short texts, so these have no lower limit. A document is out of band by its whole
    ratio, or when chunks that are out of band for their size hold more than `bad_share` of its bytes; what is left after
    the full chunks is a chunk too, with the limits of its own size.
    """

    level: int = 3
    chunk_bytes: int = 2048
    bad_share: float = 0.25
    limits: tuple[tuple[float, float, float], ...] = (
        (128, 0.0, 2.0),
        (256, 0.9, 2.5),
        (512, 1.1, 3.0),
        (1024, 1.25, 3.5),
        (2048, 1.4, 4.0),
        (8192, 1.45, 4.5),
        (32768, 1.5, 5.5),
        (float("inf"), 1.5, 7.0),
    )

    def inside(self, size: int, ratio: float) -> bool:
        low, high = next((a, b) for below, a, b in self.limits if size < below)
        return low <= ratio <= high


#: How many deviations from the fitted ratio limits allow, and the steps of a doubling that sizes and ratios are counted in.
FIT_SPREAD, SIZE_STEPS, RATIO_STEPS = 4.5, 64, 512


def _median(values: np.ndarray, weights: np.ndarray) -> float:
    order = np.argsort(values, kind="stable")
    upto = np.cumsum(weights[order])
    low, high = np.searchsorted(2 * upto, upto[-1]), np.searchsorted(2 * upto, upto[-1], side="right")
    return float(values[order][low] + values[order][high]) / 2


def bands_from_sample(sizes: np.ndarray, ratios: np.ndarray, general: CompressionBands | None = None, spread: float = FIT_SPREAD, weights: np.ndarray | None = None) -> CompressionBands:
    """Limits around the ratio that good texts of each length have, in steps of a quarter of a doubling.

    The middle is a parabola over the logarithm of the size; the deviation is that of the texts up to a doubling away, but for
    outliers beyond five deviations by the median of absolute residuals. Sizes with fewer than 20 such texts, and all sizes
    with fewer than 100 texts in all, keep the general limits. `weights` says how many texts each entry stands for.
    """
    general = general or CompressionBands()
    x = np.log2(np.maximum(1, sizes))
    n = np.ones(len(x), dtype=np.int64) if weights is None else weights
    if n.sum() < 100:
        return general
    near = np.ones(len(x), dtype=bool)
    for _ in range(3):  # texts far from the curve don't bend it
        curve = np.polyfit(x[near], ratios[near], 2, w=np.sqrt(n[near]))
        off = ratios - np.polyval(curve, x)
        away = np.abs(off - _median(off, n))
        near = away <= 5 * 1.4826 * _median(away, n) + 1e-9
    limits, steps = [], np.arange(np.ceil(4 * x.min()), np.floor(4 * x.max())) / 4
    for a in steps:
        here = near & (np.abs(x - a - 0.125) <= 1)
        own, many = off[here], n[here]
        if many.sum() < 20:
            if limits:
                break
            continue
        deviation = np.sqrt(np.average((own - np.average(own, weights=many)) ** 2, weights=many))
        room = spread * max(float(deviation), 0.01)
        middle = np.polyval(curve, [a, a + 0.25]) + _median(own, many)
        limits.append((float(2 ** (a + 0.25)), float(middle.min()) - room, float(middle.max()) + room))
    if not limits:
        return general
    least = limits[0][0] / 2**0.25
    below = [(min(size, least), low, high) for size, low, high in general.limits if size <= least] + [(least, *next((low, high) for size, low, high in general.limits if size > least - 1))]
    above = [(size, low, high) for size, low, high in general.limits if size > limits[-1][0]]
    return CompressionBands(general.level, general.chunk_bytes, general.bad_share, (*below, *limits, *above))


def labels_beside(spark: SparkSession, sf_dir: str) -> DataFrame | None:
    """The table of labels in a folder of tables, None if there is none."""
    try:
        return spark.read.parquet(f"{sf_dir}/labels.parquet")
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return None


def fitted_bands(docs: DataFrame, labels: DataFrame | None, good: str = "quality = 1", most: int | None = None, general: CompressionBands | None = None, id_col: str = "doc_id", text_col: str = "text") -> CompressionBands:
    """Limits from all texts whose label (a row of `labels` with the id) says that they are good, or from at most `most` if asked for.

    Every such text is measured whole. They are counted by size and ratio in small steps, each with the exact means of its texts, so what
    comes back grows with the spread of sizes and ratios and not with the texts. Texts are measured before the join, which
    moves numbers only. `most` texts are chosen by a hash of the id, so reruns agree. Null ids and texts take no part. Without labels the general limits hold.
    """
    general = general or CompressionBands()
    if labels is None:
        return general
    chosen = labels.filter(good).select(F.col(id_col).cast("long").alias("k")).filter("k IS NOT NULL").distinct()
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).filter("doc_id IS NOT NULL AND text IS NOT NULL")
    if most is not None:
        chosen = F.broadcast(chosen.orderBy(F.xxhash64("k"), "k").limit(most))
        texts = texts.join(chosen, F.col("doc_id") == F.col("k"), "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        z = zstandard.ZstdCompressor(level=general.level)
        for batch in batches:
            raws = [text_bytes(t, lower=False) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(r) for r in raws], pa.int64()), pa.array([len(r) / len(z.compress(r)) for r in raws], pa.float64())], names=["doc_id", "size", "ratio"])

    found = texts.mapInArrow(giving_back(run), "doc_id long, size long, ratio double")
    if most is None:
        found = found.join(chosen, F.col("doc_id") == F.col("k"), "left_semi")
    else:
        found = found.orderBy(F.xxhash64("doc_id"), "size", "ratio").limit(most)
    steps = [F.floor(SIZE_STEPS * F.log2(F.greatest("size", F.lit(1)))).alias("s"), F.floor(RATIO_STEPS * F.log2(F.greatest("ratio", F.lit(1e-6)))).alias("r")]
    sums = [F.sum("size").alias("sizes"), F.sum(F.round(F.col("ratio") * 1_000_000).cast("long")).alias("ratios"), F.count(F.lit(1)).alias("n")]  # whole numbers, so any order of adding agrees
    t = found.groupBy(*steps).agg(*sums).orderBy("s", "r").toArrow()
    n = t["n"].to_numpy()
    return bands_from_sample(t["sizes"].to_numpy() / n, t["ratios"].to_numpy() / (1_000_000 * n), general, weights=n)


_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_BLANK = " \t\r\x0b\x0c"


def _repeated_words(hashes: np.ndarray, width: int = 5) -> int:
    """Words inside a `width`-word window that occurs twice or more."""
    w = window_hashes(hashes, width)
    if len(w) < 2:
        return 0
    _, back, n = np.unique(w, return_inverse=True, return_counts=True)
    twice = np.flatnonzero(n[back] > 1)
    edge = np.zeros(len(hashes) + 1, dtype=np.int64)
    np.add.at(edge, twice, 1)
    np.add.at(edge, twice + width, -1)
    return int((np.cumsum(edge)[:-1] > 0).sum())


def _repeated_lines(text: str) -> int:
    seen, n = set(), 0
    for line in text.split("\n"):
        if line.strip(_BLANK):
            if line in seen:
                n += 1
            seen.add(line)
    return n


def compression_verdict(raw: bytes, bands: CompressionBands, compressor) -> tuple[float, int, int, bool]:
    """Whole ratio, chunks, chunks out of band, and whether the text stays; an empty text has ratio 0."""
    if not raw:
        return 0.0, 0, 0, True
    whole = len(raw) / len(compressor.compress(raw))
    if len(raw) <= bands.chunk_bytes:  # its only chunk is the whole
        fine = bands.inside(len(raw), whole)
        return whole, 1, int(not fine), fine
    n = bad = bad_bytes = 0
    for at in range(0, len(raw), bands.chunk_bytes):
        part = raw[at : at + bands.chunk_bytes]
        n += 1
        if not bands.inside(len(part), len(part) / len(compressor.compress(part))):
            bad, bad_bytes = bad + 1, bad_bytes + len(part)
    return whole, n, bad, bands.inside(len(raw), whole) and bad_bytes <= bands.bad_share * len(raw)


_FIELDS = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("word_chars", pa.int64()), ("n_symbols", pa.int64()), ("n_dup_lines", pa.int64()), ("n_repeat_words", pa.int64()), ("ratio", pa.float64()), ("n_chunks", pa.int64()), ("n_bad_chunks", pa.int64()), ("in_band", pa.bool_())]


def _measured(bands: CompressionBands):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        z = zstandard.ZstdCompressor(level=bands.level)
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            raws = [text_bytes(t, lower=False) for t in texts]
            rows = []
            for a, b in slices([len(r) for r in raws]):
                w = Words(raws[a:b])
                inner = ((w.data & 0xC0) != 0x80) & ~_SPACE[w.data]
                chars = np.concatenate([[0], np.cumsum(inner)])[w.offsets]
                marks = np.concatenate([[0], np.cumsum(_SYMBOL[w.data])])[w.offsets]
                for i in range(a, b):
                    k = i - a
                    h = w.hashes[w.bounds[k] : w.bounds[k + 1]]
                    rows.append((ids[i], len(h), int(chars[k + 1] - chars[k]), int(marks[k + 1] - marks[k]), _repeated_lines(texts[i] or ""), _repeated_words(h), *compression_verdict(raws[i], bands, z)))
            cols = zip(*rows, strict=True) if rows else [[] for _ in _FIELDS]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, _FIELDS, strict=True)], names=[n for n, _ in _FIELDS])

    return run


def quality_verdicts(docs: DataFrame, bands: CompressionBands | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Return the counts, the ratios, base_failed and kept, one row for each row of `docs`.

    base_failed: fewer than 10 words, or more than 20 % of the words stand in 5-word windows that occur twice or more.
    kept: neither base_failed nor out of the compression bands. A null text counts as empty and fails by its words; ids are
    passed through, null or repeated; an empty table gives an empty result; other columns are not read.
    """
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, ratio double, n_chunks long, n_bad_chunks long, in_band boolean"
    rows = texts.mapInArrow(giving_back(_measured(bands or CompressionBands())), schema)
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return rows.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & F.col("in_band"))


def passing_documents(docs: DataFrame, bands: CompressionBands | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs` that the rules keep, with all their columns, without a shuffle or a join.

    The verdict is taken beside the row that it is about, so null and repeated ids need no key.
    """
    names = docs.columns
    bands = bands or CompressionBands()
    measure = _measured(bands)
    at = [n.lower() for n in names].index(text_col.lower())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = pa.RecordBatch.from_arrays([pa.array(range(batch.num_rows), pa.int64()), batch.column(at)], names=["i", "t"])
            (m,) = measure(iter([own]))
            n, rep, fine = (m.column(c).to_numpy(zero_copy_only=False) for c in ("n_words", "n_repeat_words", "in_band"))
            yield batch.filter(pa.array((n >= 10) & (100 * rep <= 20 * n) & fine.astype(bool), pa.bool_()))

    return docs.mapInArrow(giving_back(run), docs.schema)
