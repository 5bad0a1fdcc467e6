"""Near-duplicate documents by min-max hashing of word shingles.

Every permutation of the shingle universe yields two signature values, the smallest and the largest image,
so half as many hash evaluations fill a signature of a given length, and both values of a permutation agree
between two sets with probability equal to their Jaccard similarity. Bands of signature values give
candidate buckets; every link is then confirmed on full shingle sets.

Skew. Texts with equal shingle sets collapse to one representative before banding. Inside a bucket nobody
emits all pairs: members are first compared with a leader of the bucket, in a few rounds with other leaders
each. What is then still in different components is put into blocks of bounded size and compared inside its block, then block
against block, through an index of each set's rarest shingles inside the task. A task keeps a forest of the components that it
joins and emits only its edges, so that no component is missed and rows grow with documents, not with pairs. All grouping keys are pre-aggregated or joined with joins that Spark
can split at run time.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from certgraph.functions.worker_memory import LARGE, give_back, giving_back
from certgraph.llm.wordhash import Words, mix, shingle_set, slices, text_bytes
from certgraph.operators.components import component_labels
from certgraph.plans.staging import Stages

#: Signature values in one band, and permutations; each permutation gives two values.
BAND_ROWS, PERMUTATIONS = 4, 56
#: How many leaders a member is compared with in each round before the rest is compared in blocks.
LEADER_ROUNDS = (1, 4)
#: Shingles of the sets that one block of documents holds when the rest is compared.
BLOCK_SHINGLES = 500_000

_rng = np.random.default_rng(77001)
_MUL = _rng.integers(0, 2**64, PERMUTATIONS, dtype=np.uint64) | np.uint64(1)
_ADD = _rng.integers(0, 2**64, PERMUTATIONS, dtype=np.uint64)
_COEF = _rng.integers(0, 2**64, BAND_ROWS, dtype=np.uint64) | np.uint64(1)


def minmax_signature(shingles: np.ndarray) -> np.ndarray:
    """Smallest and largest image of the set under each permutation, as one array of 2 * PERMUTATIONS values."""
    least, most = [], []
    for k in range(0, PERMUTATIONS, 8):
        image = (shingles[None, :] * _MUL[k : k + 8, None] + _ADD[k : k + 8, None]) >> np.uint64(32)
        least.append(image.min(axis=1))
        most.append(image.max(axis=1))
    return np.concatenate(least + most)


def band_keys(signature: np.ndarray) -> np.ndarray:
    """One 64-bit bucket key for each band; the band's number is part of the key."""
    rows = signature.reshape(-1, BAND_ROWS)
    return mix((rows * _COEF).sum(axis=1, dtype=np.uint64) + np.arange(len(rows), dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)).view(np.int64)


def _fingerprint(shingles: np.ndarray) -> tuple[int, int]:
    a = mix(shingles).sum(dtype=np.uint64) + np.uint64(len(shingles))
    b = mix(shingles * np.uint64(0xD6E8FEB86659FD93) + np.uint64(1)).sum(dtype=np.uint64)
    return int(a.view(np.int64)), int(b.view(np.int64))


def _each_set(batch: pa.RecordBatch, width: int) -> Iterator[tuple[int | None, np.ndarray]]:
    ids = batch.column(0).to_pylist()
    raws = [text_bytes(t, lower=True) for t in batch.column(1).to_pylist()]
    for a, b in slices([len(r) for r in raws]):
        w = Words(raws[a:b])
        for i in range(b - a):
            yield ids[a + i], shingle_set(w.hashes[w.bounds[i] : w.bounds[i + 1]], width)


def _signatures(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, ns, fa, fb, bands = [], [], [], [], []
            for doc, s in _each_set(batch, width):
                ids.append(doc)
                ns.append(len(s))
                live = len(s) > 0 and doc is not None
                a, b = _fingerprint(s) if live else (None, None)
                fa.append(a)
                fb.append(b)
                bands.append(band_keys(minmax_signature(s)) if live else None)
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, pa.int64()), pa.array(ns, pa.int64()), pa.array(fa, pa.int64()), pa.array(fb, pa.int64()), pa.array(bands, pa.list_(pa.int64()))],
                names=["doc_id", "n_shingles", "fp_a", "fp_b", "bands"],
            )

    return giving_back(run)


def _sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, blobs = [], []
            for doc, s in _each_set(batch, width):
                ids.append(doc)
                blobs.append(s.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(blobs, pa.binary())], names=["rep", "shingles"])

    return giving_back(run)


def _confirm(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                small, large = sorted((len(a), len(b)))
                if 100 * small < percent * large:
                    keep.append(False)
                    continue
                both = np.sort(np.concatenate([a, b]), kind="stable")
                shared = int((both[1:] == both[:-1]).sum())
                keep.append(100 * shared >= percent * (len(a) + len(b) - shared))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(keep, pa.bool_()))

    return giving_back(run)


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    a = sets.select(F.col("rep").alias("u"), F.col("shingles").alias("set_u"))
    b = sets.select(F.col("rep").alias("v"), F.col("shingles").alias("set_v"))
    both = pairs.join(a, "u").join(b, "v").select("u", "v", "set_u", "set_v")
    return both.mapInArrow(_confirm(percent), "u long, v long")


def near_duplicate_classes(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Return doc_id, n_shingles, component_id, kept, one row for each row of `docs`.

    Two documents are linked when 100 * shared >= percent * union over their sets of distinct `width`-word
    shingles (lower-cased A-Z; words are runs without ASCII white space). A text with fewer words is one shingle.
    `component_id` is the smallest id that links reach, `kept` tells whether the row has that id.

    Defined cases: a null or empty text, or one of white space, has n_shingles 0 and stands alone; a null id
    stands alone with a null component and is kept; rows that repeat an id and text get the same answer; an id
    with several texts is linked through each of them, each row by its own text; an empty table gives an empty
    result. Other columns of `docs` are not read. Shingles are compared by 64-bit hashes.
    """
    spark = docs.sparkSession
    st = Stages(spark, "neardup")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    sig = st.keep(texts.mapInArrow(_signatures(width), "doc_id long, n_shingles long, fp_a long, fp_b long, bands array<long>"), "signatures")

    live = sig.filter("fp_a IS NOT NULL")
    classes = st.keep(live.groupBy("fp_a", "fp_b").agg(F.min("doc_id").alias("rep"), F.min_by("bands", "doc_id").alias("bands")), "classes")
    banded = classes.select("rep", F.explode("bands").alias("bucket"))
    shared = banded.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("bucket")
    members = st.keep(banded.join(shared, "bucket", "left_semi"), "members")

    nodes = st.keep(members.select("rep").distinct(), "nodes")
    sets = st.keep(texts.join(nodes, texts.doc_id == nodes.rep, "left_semi").mapInArrow(_sets(width), "rep long, shingles binary").dropDuplicates(["rep"]).withColumn("n", F.octet_length("shingles") / 8), "sets")

    labels = nodes.select("rep", F.col("rep").alias("comp"))
    links = None
    for turn, most in enumerate(LEADER_ROUNDS):
        here = st.keep(_unsettled(here.drop("comp"), labels) if turn else members.withColumn("comp", F.col("rep")), f"open{turn}")
        found = st.keep(_confirmed(_leader_pairs(here, turn, most), sets, percent), f"links{turn}")
        links = found if links is None else links.unionByName(found)
        labels = _labels(st, nodes, links)
    here = st.keep(_unsettled(here.drop("comp"), labels), "open-within")
    blocks = _blocks(st, here, sets)
    links = links.unionByName(st.keep(_within_blocks(here, blocks, sets, percent), "links-within"))
    labels = _labels(st, nodes, links)
    here = st.keep(_unsettled(here.drop("comp"), labels), "open-between")
    links = links.unionByName(st.keep(_between_blocks(st, here, blocks, sets, percent), "links-between"))
    labels = _labels(st, nodes, links)
    st.drop(sets, members)

    by_class = classes.select("fp_a", "fp_b", "rep").join(labels, "rep", "left").select("fp_a", "fp_b", F.coalesce("comp", "rep").alias("component"))
    return (
        sig.select("doc_id", "n_shingles", "fp_a", "fp_b")
        .join(by_class, ["fp_a", "fp_b"], "left")
        .select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
        .withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
    )


def distinct_documents(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs`, with all their columns, that stay when one document of each near-duplicate class is kept.

    The one with the smallest id stays; of rows that repeat its id, one stays. Rows without an id all stay.
    """
    st = Stages(docs.sparkSession, "distinct")
    names = [f"c{i}" for i in range(len(docs.columns))]
    key = names[[n.lower() for n in docs.columns].index(id_col.lower())]
    found = near_duplicate_classes(docs, width, percent, id_col, text_col).filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("kept").alias("kept"), F.count(F.lit(1)).alias("n"))
    found = st.keep(found.filter("NOT kept OR n > 1"), "verdicts")
    rows = docs.toDF(*names)
    left = rows.join(found.filter("NOT kept").select(F.col("doc_id").alias("_gone")), F.col(key) == F.col("_gone"), "left_anti")
    twice = found.filter("kept").select(F.col("doc_id").alias("_twice"))
    if twice.isEmpty():
        return left.toDF(*docs.columns)
    once = left.join(twice, F.col(key) == F.col("_twice"), "left_anti")
    again = left.join(twice, F.col(key) == F.col("_twice"), "left_semi").groupBy(key).agg(F.min_by(F.struct(*names), F.xxhash64(*names)).alias("r")).select("r.*")
    return once.unionByName(again).toDF(*docs.columns)


def _labels(st: Stages, nodes: DataFrame, links: DataFrame) -> DataFrame:
    found = component_labels(links).withColumnRenamed("id", "rep")
    return st.keep(nodes.join(found, "rep", "left").select("rep", F.coalesce("comp", "rep").alias("comp")), "labels")


def _unsettled(members: DataFrame, labels: DataFrame) -> DataFrame:
    """Members of the buckets that still hold several components."""
    now = members.join(labels, "rep")
    mixed = now.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo <> hi").select("bucket")
    return now.join(mixed, "bucket", "left_semi")


def _leader_pairs(here: DataFrame, turn: int, most: int) -> DataFrame:
    """Each member with up to `most` leaders of its buckets, the ones that it shares most buckets with first."""
    order = F.xxhash64(F.lit(turn), "rep")
    lead = here.groupBy("bucket").agg(F.min(F.struct(order.alias("o"), F.col("rep").alias("leader"), F.col("comp").alias("leader_comp"))).alias("m")).select("bucket", "m.leader", "m.leader_comp")
    met = here.join(lead, "bucket").filter("comp <> leader_comp").groupBy("rep", "leader").agg(F.count(F.lit(1)).alias("n"))
    best = met.groupBy("rep").agg(F.slice(F.sort_array(F.collect_list(F.struct("n", "leader")), asc=False), 1, most).alias("best"))
    flat = best.select("rep", F.explode("best.leader").alias("leader"))
    return flat.select(F.least("rep", "leader").alias("u"), F.greatest("rep", "leader").alias("v")).distinct()


def _blocks(st: Stages, here: DataFrame, sets: DataFrame) -> DataFrame:
    """(rep, block): documents that share buckets, put into blocks of bounded size."""
    lead = here.groupBy("bucket").agg(F.min(F.xxhash64("rep")).alias("lead"))
    near = st.keep(here.select("bucket", "rep").join(lead, "bucket").groupBy("rep").agg(F.min("lead").alias("near")), "near")
    # the smallest leader two buckets away: neighbours mostly agree on it, so few blocks meet
    wider = here.select("bucket", "rep").join(near, "rep").groupBy("bucket").agg(F.min("near").alias("near"))
    home = here.select("bucket", "rep").join(wider, "bucket").groupBy("rep").agg(F.min("near").alias("home"))
    docs = home.join(sets.select("rep", "n"), "rep")
    parts = docs.groupBy("home").agg(F.ceil(F.sum("n") / BLOCK_SHINGLES).alias("parts"))
    return st.keep(docs.join(parts, "home").select("rep", F.xxhash64("home", F.pmod(F.xxhash64("rep"), "parts")).alias("block")), "blocks")


def _within_blocks(here: DataFrame, blocks: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links that join components inside each block, as few as do."""
    rows = here.select("rep", "comp").distinct().join(blocks, "rep").join(sets, "rep").select("block", "rep", "comp", "shingles")

    def run(table: pa.Table) -> pa.Table:
        return _linked(joining_links(*_columns(table), percent), table.nbytes)

    return rows.groupBy("block").applyInArrow(run, "u long, v long")


def _between_blocks(st: Stages, here: DataFrame, blocks: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between members of a bucket that lie in different components and different blocks.

    Two blocks meet if some bucket has documents of both, and in one of them a document outside the bucket's largest
    component; only such documents are looked up in the other block.
    """
    sizes = here.groupBy("bucket", "comp").agg(F.count(F.lit(1)).alias("m"))
    top = sizes.groupBy("bucket").agg(F.max_by("comp", F.struct("m", "comp")).alias("main"))
    docs = here.join(top, "bucket").groupBy("rep", "comp").agg(F.max(F.col("comp") != F.col("main")).alias("outside"))
    docs = st.keep(docs.join(blocks, "rep"), "placed")
    there = here.select("bucket", "rep").join(docs, "rep").groupBy("bucket", "block").agg(F.max("outside").alias("outside"))
    other = there.select("bucket", F.col("block").alias("b"))
    meet = st.keep(there.filter("outside").select("bucket", F.col("block").alias("a")).join(other, "bucket").filter("a <> b").select("a", "b").distinct(), "meetings")

    def side(block: str, rows: DataFrame) -> DataFrame:
        placed = rows.withColumnRenamed("block", block).join(meet, block).join(sets, "rep")
        return placed.select(*(F.col(c).alias(c) for c in ("a", "b", "rep", "comp", "shingles")))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        return _linked(joining_links(*_columns(left), percent, _columns(right)) if left.num_rows and right.num_rows else [], left.nbytes + right.nbytes)

    left, right = side("a", docs.filter("outside")), side("b", docs)
    return left.groupBy("a", "b").cogroup(right.groupBy("a", "b")).applyInArrow(run, "u long, v long")


def _columns(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids, components, all shingles one after another, and where each set begins."""
    raws = table.column("shingles").to_pylist()
    sizes = np.fromiter((len(r) // 8 for r in raws), dtype=np.int64, count=len(raws))
    flat = np.frombuffer(b"".join(raws), np.uint64)
    return table.column("rep").to_numpy(), table.column("comp").to_numpy(), flat, np.concatenate([[0], np.cumsum(sizes)])


def joining_links(ids, comps, flat, begin, percent: int, other=None) -> list[tuple[int, int]]:
    """Links that join the components of the given sets, as few as do: a forest over their labels.

    Sets whose intersection has `percent` of their union share one of the rarest shingles of each, when each gives as many as
    it can lack and one more. So only those are indexed, and sets that meet in the index in different components are compared in full. With
    `other`, links between the given sets and those are looked for, else links among the given ones.
    """
    own = len(ids)
    if other is not None:
        ids, comps = np.concatenate([ids, other[0]]), np.concatenate([comps, other[1]])
        flat, begin = np.concatenate([flat, other[2]]), np.concatenate([begin, other[3][1:] + begin[-1]])
    size = np.diff(begin)
    _, place, often = np.unique(flat, return_inverse=True, return_counts=True)
    holder = np.repeat(np.arange(len(ids)), size)
    by_rarity = np.lexsort((place, often[place], holder))
    rank = np.arange(len(flat)) - begin[holder]
    lacking = size - -(-percent * size // 100)
    rare = by_rarity[rank <= lacking[holder]]
    index = rare if other is None else rare[holder[rare] >= own]
    index = index[np.argsort(place[index], kind="stable")]
    key, value = place[index], holder[index]
    probe = rare[holder[rare] < own]
    starts = np.searchsorted(holder[probe], np.arange(own + 1))
    names, home = np.unique(comps, return_inverse=True)
    label, links = np.arange(len(names)), []
    for x in range(own):
        p = place[probe[starts[x] : starts[x + 1]]]
        lo, hi = np.searchsorted(key, p, "left"), np.searchsorted(key, p, "right")
        n = hi - lo
        met = np.unique(value[np.repeat(hi - np.cumsum(n), n) + np.arange(int(n.sum()))])
        if other is None:
            met = met[met > x]
        least, most = np.minimum(size[met], size[x]), np.maximum(size[met], size[x])
        met = met[100 * least >= percent * most]
        mine, turns = flat[begin[x] : begin[x + 1]], 1
        while len(met := met[label[home[met]] != label[home[x]]]):
            roots = label[home[met]]
            order = np.argsort(roots, kind="stable")
            met, roots = met[order], roots[order]
            now = np.arange(len(met)) - np.searchsorted(roots, roots) < turns  # a few of each component at a time
            turn, met, turns = met[now], met[~now], 4 * turns
            theirs = np.concatenate([flat[begin[y] : begin[y + 1]] for y in turn])
            at = np.minimum(np.searchsorted(mine, theirs), len(mine) - 1)
            shared = np.add.reduceat(mine[at] == theirs, np.concatenate([[0], np.cumsum(size[turn])[:-1]]), dtype=np.int64)
            for y in turn[100 * shared >= percent * (len(mine) + size[turn] - shared)]:
                a, b = label[home[x]], label[home[y]]
                if a != b:
                    label[label == b] = a
                    links.append((int(ids[x]), int(ids[y])))
    return links


def _linked(links: list[tuple[int, int]], size: int) -> pa.Table:
    """Links as a table, after a group of rows of so many bytes."""
    if size >= LARGE:
        give_back()
    return _link_table(links)


def _link_table(links: list[tuple[int, int]]) -> pa.Table:
    u, v = zip(*links, strict=True) if links else ((), ())
    return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64())})
