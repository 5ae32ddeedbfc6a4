"""Near-duplicate groups by b-bit MinHash.

1. Every text becomes the set of its word shingles; 128 minima give 25 band keys of five minima each
   and a packed signature of the low four bits of every minimum (64 bytes).
2. Rows with equal sets are one class (a 128-bit digest of the set); one representative goes on.
3. Representatives that share a band key meet. Bands with the same members count once. Inside a
   bucket the similarity of two signatures is estimated from equal four-bit cells, corrected for
   chance collisions; pairs within a margin of the threshold join, and only a spanning forest of
   them leaves the bucket, so a bucket of m members yields at most m - 1 rows.
4. The components of those edges hold every link whose ends share a band. In each component links
   are confirmed on the full shingle sets, every pair that is not yet connected, and again only a
   spanning forest is kept. The components of the confirmed links are the result.
Large buckets and components are cut into blocks, so no task ever holds an unbounded group. First each
block, with the group's first member beside it, is compared within itself; near copies are connected
then. Members that are still apart from most of their group are compared, in pairs of blocks, with all
its members they are not connected to. Nothing is capped: every unconnected pair of a bucket is
estimated, every unconnected pair of a component is confirmed; a group costs its size times the number
of its members that stay apart.

Texts of candidates are read a second time; a bounded Bloom filter of their ids leaves the others out
before the exchange.

A link of similarity s is missed only if all bands differ: (1 - s**5)**25, which is 4e-7 at 0.85 and
5e-5 at 0.8, or if the estimate is more than the margin too low (4.5 standard deviations).

Defined cases: null or blank text has an empty set and no link; a null id is in no component
(component_id null, not kept); the id is a key: rows that repeat it are one node; an empty table
gives an empty result; similarity is compared in integers (den * common >= num * union), ties link. Ids
are integers; an id that is none counts as null. Very long texts are read whole; only the named columns
are read, so others of any name cannot clash.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmix.llm.columns import narrow, small_batches
from relmix.llm.components import components
from relmix.llm.prefilter import Filter
from relmix.llm.textarrays import batch_shingles, mixed
from relmix.llm.workers import tidy
from relmix.session import stored

HASHES, BANDS, ROWS, BITS = 128, 25, 5, 4
CELLS = 64 // BITS
MARGIN = 0.15
BUCKET_BLOCK = 512  # members of a group in one block
SHINGLE_BLOCK = 65_536  # shingles of a component in one block

_RNG = np.random.default_rng(977)
_MUL = _RNG.integers(1, 2**63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _RNG.integers(0, 2**63, HASHES, dtype=np.uint64)
_BAND = _RNG.integers(1, 2**63, (BANDS, ROWS), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_LOW = np.uint64(0x1111111111111111)

FEATURES = "id bigint, n_sh bigint, d1 bigint, d2 bigint, bands array<bigint>, sig array<bigint>"


def minima(hashes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """The 128 minima of each non-empty row, by 128 multiply-add permutations of the 64-bit hashes."""
    at = offsets[:-1]
    out = np.empty((len(at), HASHES), np.uint64)
    for k in range(HASHES):
        out[:, k] = np.minimum.reduceat(hashes * _MUL[k] + _ADD[k], at)
    return out


def packed(least: np.ndarray) -> np.ndarray:
    """Low bits of the minima, 16 cells of four bits in each of eight 64-bit words."""
    cells = (mixed(least) & np.uint64(2**BITS - 1)).reshape(len(least), HASHES // CELLS, CELLS)
    return np.bitwise_or.reduce(cells << (np.arange(CELLS, dtype=np.uint64) * np.uint64(BITS)), axis=2)


def estimated(one: np.ndarray, many: np.ndarray) -> np.ndarray:
    """Collision-corrected similarity of one signature with many, from counts of equal cells."""
    diff = one ^ many
    diff |= diff >> np.uint64(2)
    diff |= diff >> np.uint64(1)
    unequal = np.bitwise_count(diff & _LOW).sum(axis=-1, dtype=np.int64)
    chance = 2.0**-BITS
    return ((HASHES - unequal) / HASHES - chance) / (1 - chance)


def _features(width: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0)
            for a, b, hashes, offsets in batch_shingles(batch.column(1), width):
                n = np.diff(offsets)
                full = np.flatnonzero(n)
                d1, d2 = np.zeros(b - a, np.uint64), np.zeros(b - a, np.uint64)
                bands, sig = np.zeros((b - a, BANDS), np.uint64), np.zeros((b - a, HASHES // CELLS), np.uint64)
                if len(full):
                    with np.errstate(over="ignore"):
                        starts = offsets[:-1][full]
                        d1[full] = np.add.reduceat(mixed(hashes ^ _ADD[0]), starts)
                        d2[full] = np.add.reduceat(mixed(hashes + _ADD[1]), starts)
                        least = minima(hashes, np.append(starts, len(hashes)))
                        sig[full] = packed(least)
                        for j in range(BANDS):
                            bands[full, j] = mixed((least[:, j * ROWS : (j + 1) * ROWS] * _BAND[j]).sum(axis=1, dtype=np.uint64) + np.uint64(j))
                lists = [pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.reshape(-1).view(np.int64))) for x in (bands, sig)]
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(n.astype(np.int64)), pa.array(d1.view(np.int64)), pa.array(d2.view(np.int64)), *lists], names=["id", "n_sh", "d1", "d2", "bands", "sig"])

    return run


def _forest(label: np.ndarray, near: Callable[[int, np.ndarray], np.ndarray], split: int | None) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the pairs that ``near`` accepts; with ``split`` only pairs across it.

    Rows of one label are connected already."""
    rows, label = len(label), label.copy()
    found = []
    for i in range(rows if split is None else split):
        other = np.arange(i + 1 if split is None else split, rows)
        other = other[label[other] != label[i]]
        if not len(other):
            continue
        hit = other[near(i, other)]
        if not len(hit):
            continue
        _, first = np.unique(label[hit], return_index=True)
        for j in hit[first]:
            found.append((i, int(j)))
        label[np.isin(label, label[hit])] = label[i]
    return found


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Tables of whole groups (columns 0-2 are the sorted group key), carrying a cut group over to the next batch."""
    rest: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
        change = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys])) + 1
        if rest:
            last = rest[-1]
            same = all(last.column(i)[-1].as_py() == batch.column(i)[0].as_py() for i in range(3))
            if not same:
                yield pa.Table.from_batches(rest)
                rest = []
        if len(change):
            cut = int(change[-1])
            yield pa.Table.from_batches([*rest, batch.slice(0, cut)])
            rest = [batch.slice(cut)]
        else:
            rest.append(batch)
    if rest:
        yield pa.Table.from_batches(rest)


def _bounds(table: pa.Table) -> np.ndarray:
    keys = [table.column(i).to_numpy() for i in range(3)]
    change = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys])) + 1
    return np.concatenate([[0], change, [table.num_rows]])


def _edges(u: list, v: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.asarray(u, np.int64)), pa.array(np.asarray(v, np.int64))], names=["u", "v"])


def _bucket_edges(least: float) -> Callable:
    """Rows (key, i, j, side, id, label, sig) sorted by key and blocks -> candidate edges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _groups(batches):
            table = table.combine_chunks()
            side, ids, label = (table.column(i).to_numpy() for i in (3, 4, 5))
            sig = table.column(6).combine_chunks().flatten().to_numpy().view(np.uint64).reshape(len(ids), -1)
            bounds = _bounds(table)
            size = np.diff(bounds)
            two = bounds[:-1][size == 2]
            two = two[(side[two] == side[two + 1]) == (table.column(1).to_numpy()[two] == table.column(2).to_numpy()[two])]
            ok = two[estimated(sig[two], sig[two + 1]) >= least] if len(two) else two
            u, v = ids[ok].tolist(), ids[ok + 1].tolist()
            for a, n in zip(bounds[:-1][size > 2], size[size > 2], strict=True):
                order = a + np.argsort(side[a : a + n], kind="stable")
                s, own = sig[order], ids[order]
                across = int((side[a : a + n] == 0).sum()) if table.column(1)[int(a)].as_py() != table.column(2)[int(a)].as_py() else None
                for i, j in _forest(label[order], lambda i, o, s=s: estimated(s[i], s[o]) >= least, across):
                    u.append(own[i])
                    v.append(own[j])
            yield _edges(u, v)

    return run


def _confirmed_edges(num: int, den: int) -> Callable:
    """Rows (component, i, j, side, id, label, set as bytes) sorted by component and blocks -> confirmed edges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _groups(batches):
            bounds = _bounds(table)
            side, ids, label = (table.column(i).to_numpy() for i in (3, 4, 5))
            blobs = table.column(6)
            u, v = [], []
            for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
                if b - a < 2:
                    continue
                order = a + np.argsort(side[a:b], kind="stable")
                sets = [np.frombuffer(blobs[int(r)].as_buffer(), np.uint64) for r in order]
                size = np.array([len(x) for x in sets])
                names, flat = np.unique(np.concatenate(sets), return_inverse=True)
                starts = np.concatenate([[0], np.cumsum(size)])
                mark = np.zeros(len(names), bool)

                def near(i: int, other: np.ndarray, flat=flat, starts=starts, size=size, mark=mark) -> np.ndarray:
                    mark[flat[starts[i] : starts[i + 1]]] = True
                    common = np.add.reduceat(mark[flat].view(np.uint8), starts[:-1], dtype=np.int64)[other]
                    mark[flat[starts[i] : starts[i + 1]]] = False
                    return den * common >= num * (size[i] + size[other] - common)

                across = int((side[a:b] == 0).sum()) if table.column(1)[a].as_py() != table.column(2)[a].as_py() else None
                for i, j in _forest(label[order], near, across):
                    u.append(ids[order[i]])
                    v.append(ids[order[j]])
            yield _edges(u, v)

    return run


def _sets(width: int) -> Callable:
    """(bigint columns, text) -> the same with the text's shingle set as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, hashes, offsets in batch_shingles(batch.column(batch.num_columns - 1), width):
                raw = hashes.tobytes()
                blobs = [raw[8 * x : 8 * y] for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(a, b - a) for i in range(batch.num_columns - 1)), pa.array(blobs, pa.binary())], names=[*batch.schema.names[:-1], "sh"])

    return run


def _shingled(rows: DataFrame, width: int) -> DataFrame:
    return rows.mapInArrow(tidy(_sets(width)), ", ".join(f"{c} bigint" for c in rows.columns[:-1]) + ", sh binary")


def _own_block(key: str, blocks: str, seed: int = 0):
    return F.pmod(F.xxhash64("id", F.col(key), F.lit(seed)), F.col(blocks).cast("bigint"))


def _dealt(rows: DataFrame) -> DataFrame:
    return rows.repartition(F.col("key"), F.col("bi"), F.col("bj")).sortWithinPartitions("key", "bi", "bj", "side", "id")


def _blocks(rows: DataFrame, payload: str) -> DataFrame:
    """(key, nb, first, id, payload) -> each row in its block of the group, the group's first member in every block."""
    own = _own_block("key", "nb")
    every = F.sequence(F.lit(0).cast("bigint"), F.col("nb").cast("bigint") - 1)
    at = F.explode(F.when(F.col("id") == F.col("first"), every).otherwise(F.array(own)))
    return _dealt(rows.select("key", at.alias("bi"), "id", payload).select("key", "bi", F.col("bi").alias("bj"), F.lit(0).alias("side"), "id", F.col("id").alias("label"), payload))


def _n_blocks(members, shingles=None):
    """Blocks for so many members, and shingles where full sets are compared."""
    by_members = F.ceil(members / BUCKET_BLOCK)
    return by_members if shingles is None else F.greatest(by_members, F.ceil(shingles / SHINGLE_BLOCK))


def _apart(rows: DataFrame, joined: DataFrame, shingles: str | None = None) -> DataFrame | None:
    """Groups of several blocks whose members are not all connected: (key, id, label, most, nb, nr), None without any.

    ``most`` is the label that most members of the group have; ``nr`` blocks hold the others, ``nb`` those with it.
    """
    several = rows.filter("nb > 1").select("key", "id", (F.col(shingles) if shingles else F.lit(0)).cast("bigint").alias("w"))
    labelled = several.join(joined.withColumnRenamed("node", "id"), "id", "left").select("key", "id", "w", F.coalesce("root", "id").alias("label"))
    labelled = stored(labelled, "near-labels")
    counts = labelled.groupBy("key", "label").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("w"))
    most = F.max_by(F.struct("label", "n", "w"), F.struct("n", -F.col("label")))
    groups = counts.groupBy("key").agg(F.count(F.lit(1)).alias("labels"), most.alias("most"), F.sum("n").alias("n"), F.sum("w").alias("w")).filter("labels > 1")
    of_most, of_rest = (_n_blocks(n, w) for n, w in ((F.col("most.n"), F.col("most.w")), (F.col("n") - F.col("most.n"), F.col("w") - F.col("most.w"))))
    groups = stored(groups.select("key", F.col("most.label").alias("most"), of_most.alias("nb"), of_rest.alias("nr")), "near-apart")
    return None if groups.isEmpty() else labelled.join(groups, "key").select("key", "id", "label", "most", "nb", "nr")


def _block_pairs(rows: DataFrame, payload: str) -> DataFrame:
    """Rows of ``_apart`` with a payload: the members that are apart meet each other and all the rest, in pairs of blocks."""
    upto = lambda n: F.sequence(F.lit(0).cast("bigint"), n.cast("bigint") - 1)
    nr = F.col("nr").cast("bigint")
    rest = rows.filter("label != most").withColumn("own", _own_block("key", "nr", 1)).withColumn("other", F.explode(upto(F.col("nr") + F.col("nb"))))
    low, high = F.least("own", "other"), F.greatest("own", "other")
    rest = rest.select("key", low.alias("bi"), high.alias("bj"), F.when(F.col("own") <= F.col("other"), 0).otherwise(1).alias("side"), "id", "label", payload)
    main = rows.filter("label = most").withColumn("bi", F.explode(upto(F.col("nr"))))
    main = main.select("key", "bi", (nr + _own_block("key", "nb")).alias("bj"), F.lit(1).alias("side"), "id", "label", payload)
    return _dealt(rest.unionAll(main))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """(id, n_shingles, component_id, kept) for every row; links have den * common >= num * union."""
    texts = narrow(docs, id=id_col, text=text_col).select(F.col("id").cast("bigint").alias("id"), "text")
    rows = stored(small_batches(texts).mapInArrow(tidy(_features(width)), FEATURES), "near-features")
    usable = rows.filter("n_sh > 0 AND id IS NOT NULL")
    classes = usable.groupBy("d1", "d2", "n_sh").agg(F.min("id").alias("rep"), F.first("bands").alias("bands"), F.first("sig").alias("sig"))
    reps = stored(classes, "near-classes")
    edges_of = lambda dealt, compare: dealt.mapInArrow(tidy(compare), "u bigint, v bigint")

    # buckets: band keys that several representatives share, one for each set of members
    keyed = reps.select(F.explode("bands").alias("key"), F.col("rep").alias("id"))
    shared = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("first"), F.expr("bit_xor(xxhash64(id))").alias("x1"), F.expr("bit_xor(xxhash64(id, 7))").alias("x2")).filter("n > 1")
    shared = shared.groupBy("n", "first", "x1", "x2").agg(F.min("key").alias("key")).select("key", "first", _n_blocks(F.col("n")).alias("nb"))
    members = stored(keyed.join(shared, "key"), "near-members")
    sigs = reps.select(F.col("rep").alias("id"), "sig")
    estimate = _bucket_edges(num / den - MARGIN)
    candidates = stored(edges_of(_blocks(members.join(sigs, "id"), "sig"), estimate), "near-edges")
    grouped = components(candidates)
    apart = _apart(members, grouped)
    if apart is not None:
        grouped = components(candidates.unionAll(edges_of(_block_pairs(apart.join(sigs, "id"), "sig"), estimate)))

    # confirm on full sets inside each component of candidates
    held = stored(grouped.join(reps.select(F.col("rep").alias("node"), "n_sh"), "node"), "near-candidates")
    sizes = held.groupBy("root").agg(_n_blocks(F.count(F.lit(1)), F.sum("n_sh")).alias("nb"))
    chosen = held.join(sizes, "root").select(F.col("root").alias("key"), "nb", F.col("root").alias("first"), F.col("node").alias("id"), "n_sh")
    likely = Filter(held.select("node")).possible(texts, F.col("id"))
    # merged at every size: the candidates grow with the data, so neither side may be broadcast
    shingled = lambda found, kept, *names: _shingled(found.join(kept.hint("merge"), "id").select(*names, "text"), width)
    confirm = _confirmed_edges(num, den)
    links = stored(edges_of(_blocks(shingled(likely, chosen, "key", "nb", "first", "id"), "sh"), confirm), "near-links")
    linked = components(links)
    apart = _apart(chosen, linked, "n_sh")
    if apart is not None:
        # the same texts once more, those of the groups that are still apart
        few = Filter(apart.select("id")).possible(texts, F.col("id"))
        sets = shingled(few, apart, "key", "nb", "nr", "id", "label", "most")
        linked = components(links.unionAll(edges_of(_block_pairs(sets, "sh"), confirm)))

    roots = reps.select("d1", "d2", "n_sh", "rep").join(linked.withColumnRenamed("node", "rep"), "rep", "left").select("d1", "d2", "n_sh", F.coalesce("root", "rep").alias("root"))
    out = rows.select("id", "n_sh", "d1", "d2").join(roots, ["d1", "d2", "n_sh"], "left")
    component = F.when(F.col("n_sh") > 0, F.col("root")).otherwise(F.col("id"))
    component = F.when(F.col("id").isNotNull(), component)
    return out.select("id", F.col("n_sh").alias("n_shingles"), component.alias("component_id"), (F.col("id").eqNullSafe(component) & F.col("id").isNotNull()).alias("kept"))


def surviving(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One document of each group, in the input's columns. Rows with a null id stay (they have no group)."""
    dropped = near_duplicates(docs, id_col, text_col, **options).filter("NOT kept AND id IS NOT NULL").select(F.col("id").alias("__gone")).distinct()
    return docs.join(dropped, F.col(f"`{id_col}`").cast("bigint") == F.col("__gone"), "left_anti")


def op8_near_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_duplicates(docs, width=3, num=85, den=100).withColumnRenamed("id", "doc_id")
