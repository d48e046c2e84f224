"""SimHash near-duplicates with pigeonring candidate filtering.

Fingerprint: A-Z lower-cased words, three-word shingles with repeats, XXH64 (seed 42); a bit is set if it is set in
over half of the shingles. Links: fingerprints that differ in at most two of 64 bits.

The 64 bits form a ring of 16 segments. If two fingerprints differ in at most two bits, then from some segment on every
chain of l consecutive segments differs in at most 2 l / 16 bits: none in the first seven, one at most up to the
fifteenth, two in all. So the seven segments after each start are an equi-join key (28 bits), the chain's budget prunes
what meets there, and only then the whole distance is counted. Fingerprints, not documents, are compared, so copies
meet once. What shares a key is sorted and streamed through one task as plain numbers; a run of fingerprints gives the
edges of its components' stars and never its pairs. Runs over ``BLOCK_RUN`` are linked through values with two bits
masked, which needs no pairs either. A run over ``HOT_RUN`` is not gathered but dealt again: of the 36 bits that its
members may differ in, two differ at most, so one of three blocks of 12 is equal too and joins the key; where that is
hot as well, one of three blocks of 8 of the 24 bits that are left. Then 16 bits are free, and a run has 65,536 members.

Defined results: null, empty and wordless texts have fingerprint zero and are linked like any other; a component's id
is its smallest doc_id, null only if all are null; repeated rows each get a row; an empty table gives no rows; other
columns are ignored by ``near_duplicates`` and kept by ``keep_one``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import remove, write_table, written
from .components import components

SHINGLE, SEED, DISTANCE = 3, 42, 2
SEGMENTS, WIDTH = 16, 4
CHAIN = SEGMENTS // DISTANCE - 1  # so many whole segments have a budget under one bit
BLOCK_RUN, HOT_RUN = 4096, 1 << 16
KEEP_BROADCAST = 2_000_000


def fingerprint(text: str | None) -> int:
    """The unsigned 64-bit fingerprint of one text."""
    import xxhash

    words = (text or "").encode().lower().split()  # bytes: only A-Z change, and only the six ASCII blanks part words
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = max(1, len(words) - SHINGLE + 1)
    stops = ends[min(SHINGLE, len(words)) - 1 :]
    digest = xxhash.xxh64_intdigest
    return majority_bits(np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), stops.tolist(), strict=True)), np.uint64, n))


def majority_bits(h: np.ndarray) -> int:
    """The unsigned fingerprint of shingle hashes: the bits that are set in over half of them."""
    n = len(h)
    counts = np.zeros(64, np.int64)
    for i in range(0, n, 1 << 15):
        part = h[i : i + (1 << 15)].astype("<u8")
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    bits = np.packbits(2 * counts > n, bitorder="little")
    return int(bits.view("<u8")[0])


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_hash, fp) for each document; fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t.as_py()) for t in b.column(2)), np.uint64, b.num_rows).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fp)], ["doc_id", "text_hash", "fp"])

    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("text_hash"), text.alias("text"))
    return rows.mapInArrow(run, "doc_id long, text_hash long, fp long")


def _turned(fp, start: int):
    return fp if not start else F.shiftleft(fp, WIDTH * start).bitwiseOR(F.shiftrightunsigned(fp, 64 - WIDTH * start))


def _chain_mask(start: int) -> np.uint64:
    """The bits of all segments after ``start`` but the last."""
    low = ((1 << 64) - 1) >> WIDTH << WIDTH  # the turned value without its last segment
    turn = WIDTH * start
    return np.uint64(((low >> turn) | (low << (64 - turn))) & ((1 << 64) - 1) if turn else low)


def link_run(fps: np.ndarray, start: int) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (member, root) of the components among distinct fingerprints that share the chain after ``start``."""
    n = len(fps)
    label = np.arange(n)
    if n <= BLOCK_RUN:
        mask = _chain_mask(start)
        near = np.zeros((n, n), bool)
        for a in range(0, n, 256):
            x = fps[a : a + 256, None] ^ fps[None, :]
            ok = np.bitwise_count(x & mask) <= 1
            near[a : a + 256] = ok & (np.bitwise_count(x) <= DISTANCE)
        while True:
            new = np.where(near, label[None, :], n).min(1)
            new = new[new]
            if (new == label).all():
                break
            label = new
    else:
        low = [b for b in range(64) if not (int(_prefix_mask(start)) >> b) & 1]
        while True:
            before = label.copy()
            for i, p in enumerate(low):
                for q in low[i + 1 :]:
                    key = fps & ~np.uint64((1 << p) | (1 << q))
                    order = np.argsort(key, kind="stable")
                    heads = np.flatnonzero(np.r_[True, key[order][1:] != key[order][:-1]])
                    least = np.repeat(np.minimum.reduceat(label[order], heads), np.diff(np.r_[heads, n]))
                    label[order] = np.minimum(label[order], least)
            label = np.minimum(label, label[label])
            if (label == before).all():
                break
    moved = label != np.arange(n)
    return fps[moved], fps[label[moved]]


def _prefix_mask(start: int) -> np.uint64:
    """The bits of the CHAIN segments that are equal in a run."""
    top = ((1 << (WIDTH * CHAIN)) - 1) << (64 - WIDTH * CHAIN)
    turn = WIDTH * start
    return np.uint64(((top >> turn) | (top << (64 - turn))) & ((1 << 64) - 1) if turn else top)


def _runs(hot_run: int):
    """Linker of runs of equal (start, key, sub) in sorted batches: rows (kind 0, u, v) are edges; the members of a run
    over ``hot_run`` come back as (kind 1, start, key, sub, fp) and are not held."""
    names = ["kind", "u", "v", "start", "key", "sub"]

    def out(kind: int, u: np.ndarray, v: np.ndarray | None, run: tuple) -> pa.RecordBatch:
        n = len(u)
        cols = [np.full(n, kind, np.int32), u.view(np.int64), (u if v is None else v).view(np.int64), *[np.full(n, x, np.int64) for x in run]]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names)

    def run_(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        held_key, held_n, hot = None, 0, False

        def flush():
            if held_key is not None and held_n > 1:
                fps = np.concatenate(held).view(np.uint64)
                if hot:
                    yield out(1, fps, None, held_key)
                else:
                    yield out(0, *link_run(fps, held_key[0]), (0, 0, 0))

        for batch in batches:
            if not batch.num_rows:
                continue
            start, key, sub, fp = (np.asarray(batch.column(i)) for i in range(4))
            heads = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]) | (start[1:] != start[:-1]) | (sub[1:] != sub[:-1])])
            ends = np.r_[heads[1:], len(fp)]
            us, vs = [], []
            for i, (a, z) in enumerate(zip(heads.tolist(), ends.tolist(), strict=True)):
                this = (int(start[a]), int(key[a]), int(sub[a]))
                if this != held_key:
                    if held_key is not None:
                        yield from flush()
                        held, held_key, held_n, hot = [], None, 0, False
                    if i < len(heads) - 1 and z - a <= hot_run:  # the run ends in this batch
                        if z - a > 1:
                            u, v = link_run(fp[a:z].copy().view(np.uint64), this[0])
                            us.append(u), vs.append(v)
                        continue
                    held_key = this
                held.append(fp[a:z].copy())
                held_n += z - a
                hot = hot or held_n > hot_run
                if hot:
                    yield from flush()
                    held = [np.zeros(0, np.int64)]
            if us:
                yield out(0, np.concatenate(us), np.concatenate(vs), (0, 0, 0))
        if not hot:
            yield from flush()

    return run_


FREE = 64 - WIDTH * CHAIN  # bits in which the members of a run may differ


def _dealt_again(hot: DataFrame, level: int) -> DataFrame:
    """(start, key, sub, fp): the members of hot runs under each block of bits that could be equal too."""
    free = F.lit(0)
    for i in range(SEGMENTS):
        free = F.when(F.col("start") == i, _turned(F.col("fp"), i).bitwiseAND((1 << FREE) - 1)).otherwise(free)
    rows = hot.withColumn("free", free)
    if level == 1:
        blocks = [F.lit((i + 1) << 12).bitwiseOR(F.shiftright("free", 12 * i).bitwiseAND(0xFFF)) for i in range(3)]
    else:
        block = F.shiftright("sub", 12) - 1
        low = F.when(block == 0, F.shiftright("free", 12).bitwiseAND(0xFFF)).otherwise(F.col("free").bitwiseAND(0xFFF))
        high = F.when(block == 2, F.shiftright("free", 12).bitwiseAND(0xFFF)).otherwise(F.shiftright("free", 24).bitwiseAND(0xFFF))
        left = low.bitwiseOR(F.shiftleft(high, 12))
        blocks = [F.shiftleft("sub", 10).bitwiseOR(F.lit((i + 1) << 8)).bitwiseOR(F.shiftright(left, 8 * i).bitwiseAND(0xFF)) for i in range(3)]
    return rows.select("start", "key", F.explode(F.array(*blocks)).alias("sub"), "fp")


def links(distinct: DataFrame, hot_run: int = HOT_RUN) -> DataFrame:
    """(u, v): star edges that connect what lies within DISTANCE bits, from a table of distinct fingerprints (fp)."""
    fp = F.col("fp")
    places = F.array(*[F.struct(F.lit(i).cast("long").alias("start"), F.shiftrightunsigned(_turned(fp, i), FREE).alias("key")) for i in range(SEGMENTS)])
    spread = distinct.select(F.inline(places), F.lit(0).cast("long").alias("sub"), "fp")
    found = None
    for level in (1, 2, 3):
        met = spread.repartition("start", "key", "sub").sortWithinPartitions("start", "key", "sub", "fp")
        # at the third level a run can't be hot: 2^16 fingerprints share its other bits
        rows = written(met.mapInArrow(_runs(hot_run if level < 3 else 1 << 62), "kind int, u long, v long, start long, key long, sub long"), "simhash-links")
        edges = rows.where("kind = 0").select("u", "v")
        found = edges if found is None else found.unionByName(edges)
        hot = rows.where("kind = 1").select("start", "key", "sub", F.col("u").alias("fp"))
        if level == 3 or hot.isEmpty():
            return found
        spread = _dealt_again(hot, level)


def nearest_in_run(fps: np.ndarray, start: int, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """(member, partner) positions: for each fingerprint of a run the nearest one before it within ``distance`` bits, pruned
    by the budget of every chain after ``start``."""
    turned = fps if not start else (fps << np.uint64(WIDTH * start)) | (fps >> np.uint64(64 - WIDTH * start))
    chains = [(np.uint64((1 << 64) - (1 << (64 - WIDTH * n))), n * distance // SEGMENTS) for n in range(2, SEGMENTS) if (n + 1) * distance // SEGMENTS > n * distance // SEGMENTS]
    members, partners = [], []
    for a in range(0, len(fps), 256):
        x = turned[a : a + 256, None] ^ turned[None, : a + 256]
        far = np.bitwise_count(x).astype(np.int16)
        ok = (far <= distance) & (np.arange(x.shape[1])[None, :] < np.arange(a, a + x.shape[0])[:, None])
        for mask, budget in chains:
            ok &= np.bitwise_count(x & mask) <= budget
        far[~ok] = 99
        best = far.argmin(1)
        hit = np.flatnonzero(far[np.arange(len(best)), best] < 99)
        members.append(hit + a), partners.append(best[hit])
    return np.concatenate(members), np.concatenate(partners)


def nearest(marked: DataFrame, distance: int, run: int = BLOCK_RUN) -> DataFrame:
    """(u, v): pairs of marks within ``distance`` bits for an exact check, from (mark, fp), fp the fingerprint of what the
    mark names. The same ring: the segments after each start that a budget under one bit leaves equal are the join key.

    A mark is paired with its nearest one of each run, so there are at most 16 pairs a mark and never those of a whole group.
    Runs are taken in pieces of ``run``; callers have an exact way for the pairs that are not given."""
    chain = -(-SEGMENTS // distance) - 1
    if chain < 1:
        raise ValueError("distance leaves no whole segment to join by")
    fp = F.col("fp")
    places = F.array(*[F.struct(F.lit(i).cast("long").alias("start"), F.shiftrightunsigned(_turned(fp, i), 64 - WIDTH * chain).alias("key")) for i in range(SEGMENTS)])

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []  # (start, key, fp, mark) of the run that may go on

        def linked(rows: np.ndarray) -> pa.RecordBatch:
            heads = np.flatnonzero(np.r_[True, (rows[1:, 0] != rows[:-1, 0]) | (rows[1:, 1] != rows[:-1, 1])])
            us, vs = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for a, z in zip(heads.tolist(), np.r_[heads[1:], len(rows)].tolist(), strict=True):
                for at in range(a, z, run):
                    part = rows[at : min(at + run, z)]
                    if len(part) > 1:
                        i, j = nearest_in_run(part[:, 2].copy().view(np.uint64), int(part[0, 0]), distance)
                        us.append(part[i, 3]), vs.append(part[j, 3])
            u, v = np.concatenate(us), np.concatenate(vs)
            return pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v))], ["u", "v"])

        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(np.stack([np.asarray(batch.column(i)) for i in range(4)], axis=1))
            rows = np.concatenate(held)
            new = np.flatnonzero((rows[:, 0] != rows[-1, 0]) | (rows[:, 1] != rows[-1, 1]))
            done = int(new[-1]) + 1 if len(new) else 0
            done += (len(rows) - done) // run * run  # whole pieces of the last run
            if done:
                yield linked(rows[:done])
            held = [rows[done:]]
        if held and len(held[0]):
            yield linked(held[0])

    spread = marked.select(F.inline(places), "fp", "mark").repartition("start", "key").sortWithinPartitions("start", "key", "fp", "mark")
    return spread.mapInArrow(pairs, "u long, v long")


def _classes(marks: DataFrame) -> DataFrame:
    """(fp, root): every fingerprint with its component's root."""
    distinct, path = write_table(marks.select("fp").distinct(), "fp")
    roots = components(links(distinct))
    out = distinct.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"))
    return out


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fingerprint, component_id) for each document."""
    marks = written(fingerprints(docs, id_col=id_col, text_col=text_col), "fingerprints")
    of_fp = _classes(marks)
    least = marks.groupBy("fp").agg(F.min("doc_id").alias("least"))
    named = of_fp.join(least, "fp")
    ids = named.groupBy("root").agg(F.min("least").alias("component_id"))
    of_fp = named.join(ids, "root").select("fp", "component_id")
    return marks.join(of_fp, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents with all their columns, one row for each component: that of the smallest doc_id (null last).

    What goes is found on slim rows and anti-joined by id and text hash; texts move only if that list is too long to
    broadcast. Rows equal in both are told apart only if some stay, and then one of them is kept.
    """
    marks = written(fingerprints(docs, id_col=id_col, text_col=text_col), "fingerprints")
    return keep_smallest(docs, marks, _classes(marks), id_col=id_col, text_col=text_col)


def keep_smallest(docs: DataFrame, marks: DataFrame, classes: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row for each root of ``classes`` (fp, root); marks: (doc_id, text_hash, fp) of each document."""
    spark = docs.sparkSession
    of_fp, path = write_table(classes, "classes")
    row = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_hash")
    best = marks.join(of_fp, "fp").groupBy("root").agg(F.min(row).alias("best")).select("root", "best.doc_id", "best.text_hash")
    kept, kept_path = write_table(best, "kept")
    same = lambda a, b: a["doc_id"].eqNullSafe(b["doc_id"]) & (a["text_hash"] == b["text_hash"])
    gone = marks.join(kept, same(marks, kept), "left_anti").select("doc_id", "text_hash").distinct()
    gone, gone_path = write_table(gone.toDF("gone_id", "gone_hash"), "gone")
    twice = marks.join(kept, same(marks, kept), "left_semi").groupBy("doc_id", "text_hash").count().where("count > 1").limit(1).count()
    id_, hash_ = docs[id_col].cast("long"), F.xxhash64(F.coalesce(docs[text_col].cast("string"), F.lit("")))
    listed = F.broadcast(gone) if gone.count() <= KEEP_BROADCAST else gone
    out = docs.join(listed, id_.eqNullSafe(gone["gone_id"]) & (hash_ == gone["gone_hash"]), "left_anti")
    remove(spark, path, kept_path)
    if twice:
        row = out.select(F.struct("*").alias("row"), out[id_col].cast("long").alias("i"), F.xxhash64(F.coalesce(out[text_col].cast("string"), F.lit(""))).alias("h"))
        out = row.dropDuplicates(["i", "h"]).select("row.*")
    return out
