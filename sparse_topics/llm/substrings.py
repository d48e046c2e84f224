"""Repeated-substring removal with threshold-bounded interval expansion on a Burrows-Wheeler transform.

A byte goes if a string of ``LENGTH`` bytes covers it that also starts in a document with a smaller doc_id.

How it is dealt out. Every window of LENGTH bytes has a minimizer, its K-gram of least hash; equal windows have equal
minimizers, so windows that share a minimizer form a segment and segments can be dealt to shards by it. Documents are
packed into compressed pages, kept in files of the shared folder and fetched by range. (1) Each page sends the distinct minimizers of its windows, as plain hashes, to the
shards; the shards answer with one bit for each: does it occur in more than one document? (2) Pages send the segments
whose minimizer does, each different one once with its smallest doc_id. A shard builds the transform of its different
segments and expands all intervals breadth-first by backward extension: after step l the interval borders are those
rows whose common prefix with the row above is below l, so common prefixes come out by increasing value, and the
expansion ends at LENGTH. The intervals left are the windows with equal bytes; each gets its smallest doc_id. A
minimizer whose segments are all the same bytes needs no expansion beyond that merge. (3) The shards answer with one
bit for each window, and pages mark what goes. All that moves is hashes, bits and segments that
repeat; a passage in very many documents moves once a page; the segments of a minimizer that lies in more than
``HOT_PAGES`` pages are dealt by the windows' own hash.

Defined results: a null text is empty; a null doc_id comes after all others (and no null is before another); rows with
equal doc_id do not remove each other's bytes; texts under LENGTH bytes stay whole; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import TaskFile, file_system, fresh_path, make_folder, release, written

LENGTH, K = 50, 24  # K: a multiple of 8
PAGE_BYTES = 1 << 20
SHARD_BYTES = 6 << 20
PAGES_A_TASK = 8
HOT_PAGES = 20_000
NULL_ID = (1 << 63) - 1
_POSITION_BITS = 23
_CHUNK = (1 << _POSITION_BITS) - LENGTH
PAGES = "page long, ids binary, lens binary, file string, offset long, length long, n_bytes long"


def _pack(level: int = 3):
    import zstandard

    return zstandard.ZstdCompressor(level=level).compress


def _unpack(data: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(data)


# ---- windows and minimizers -----------------------------------------------------------------------------------------


def _grams(t: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the K bytes from each position."""
    b = t.astype(np.uint64)
    for shift in (1, 2, 4):
        b = b[:-shift] | (b[shift:] << np.uint64(8 * shift))
    n = len(t) - K + 1
    h = b[:n] * np.uint64(0x9E3779B97F4A7C15)
    for at in range(8, K, 8):
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xD6E8FEB86659FD93)
        h += b[at : at + n] * np.uint64(0xC2B2AE3D27D4EB4F)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    return h


def _slide(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of ``width`` values."""
    have = 1
    while 2 * have <= width:
        x = np.minimum(x[:-have], x[have:])
        have *= 2
    more = width - have
    return np.minimum(x[:-more], x[more:]) if more else x


def segments(t: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, stop, minimizer hash) of the maximal runs of windows with one minimizer; t holds documents end to end."""
    out: list[tuple] = []
    n = len(t)
    last = np.zeros(n, bool)  # windows that would cross the end of a document
    for back in range(1, LENGTH):
        at = stops - back
        last[at[(at >= 0)]] = True
    for a in range(0, max(0, n - LENGTH + 1), _CHUNK):
        part = t[a : a + _CHUNK + LENGTH - 1]
        h = _grams(part)
        low = np.uint64((1 << _POSITION_BITS) - 1)
        least = _slide((h & ~low) | np.arange(len(h), dtype=np.uint64), LENGTH - K + 1)
        good = ~last[a : a + len(least)]
        new = good.copy()
        new[1:] &= ~good[:-1] | (least[1:] != least[:-1])
        starts = np.flatnonzero(new)
        if not len(starts):
            continue
        ends = good.copy()
        ends[:-1] &= ~good[1:] | new[1:]
        out.append((starts + a, np.flatnonzero(ends) + a + LENGTH, h[(least[starts] & low).astype(np.int64)]))
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


class Page:
    """One page and the segments of its windows."""

    def __init__(self, ids: bytes, lens: bytes, data: bytes):
        self.ids, lens_ = np.frombuffer(ids, np.int64), np.frombuffer(lens, np.int64)
        self.data = _unpack(data)
        self.stops = np.cumsum(lens_)
        self.starts = self.stops - lens_
        self.bytes = np.frombuffer(self.data, np.uint8)
        self.seg_start, self.seg_stop, self.seg_hash = segments(self.bytes, self.stops)
        self.seg_doc = np.searchsorted(self.stops, self.seg_start, side="right")

    def minimizers(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(distinct hashes, whether one occurs under several doc_ids, the segments' places among them)."""
        distinct, place = np.unique(self.seg_hash, return_inverse=True)
        ids = self.ids[self.seg_doc]
        least, most = np.full(len(distinct), NULL_ID), np.full(len(distinct), -(1 << 63))
        np.minimum.at(least, place, ids)
        np.maximum.at(most, place, ids)
        return distinct, least != most, place


def shard_of(h: np.ndarray, shards: int) -> np.ndarray:
    return ((h >> np.uint64(24)) % np.uint64(shards)).astype(np.int64)


def _by_shard(h: np.ndarray, shards: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, shard numbers, heads): the distinct hashes shard by shard, each in ascending order."""
    s = shard_of(h, shards)
    order = np.argsort(s, kind="stable")
    heads = np.flatnonzero(np.r_[True, s[order][1:] != s[order][:-1]]) if len(s) else np.zeros(0, np.int64)
    return order, s[order][heads] if len(s) else s, heads


def _spans(heads: np.ndarray, n: int) -> list[tuple[int, int]]:
    return list(zip(heads.tolist(), [*heads[1:].tolist(), n][: len(heads)], strict=True))


def _bits(x: np.ndarray) -> bytes:
    return np.packbits(x).tobytes()


def _unbits(b: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(b, np.uint8), count=n).astype(bool)


# ---- step 0: pages --------------------------------------------------------------------------------------------------


def pages_of(docs: DataFrame, folder: str, id_col: str, text_col: str) -> DataFrame:
    """Writes the pages into files under ``folder``; gives the index of the pages."""
    make_folder(docs.sparkSession, folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task = TaskContext.get()
        part, ids, texts, size, out = task.partitionId(), [], [], 0, []
        name, file, pack = f"pages-{part:06d}", None, _pack()

        def page():
            data = b"".join(texts)
            packed = pack(data)
            lens = np.array([len(x) for x in texts], np.int64)
            out.append(((part << 32) + len(out), np.array(ids, np.int64).tobytes(), lens.tobytes(), name, file.write(packed), len(packed), len(data)))

        for b in batches:
            for i, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                text = (t.as_py() or "").encode()
                file = file or TaskFile(folder, name, task.taskAttemptId())
                if texts and size + len(text) > PAGE_BYTES:
                    page()
                    ids, texts, size = [], [], 0
                ids.append(NULL_ID if i is None else i), texts.append(text)
                size += len(text)
        if texts:
            page()
        if file:
            file.close()
            kinds = (pa.int64(), pa.binary(), pa.binary(), pa.string(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], [f.split()[0] for f in PAGES.split(", ")])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, PAGES)


def _fetched(folder: str, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[dict, Page]]:
    """Each row with its page, read by range."""
    fs, base = file_system(folder)
    name, file = None, None
    for b in batches:
        for r in b.to_pylist():
            if r["file"] != name:
                name, file = r["file"], fs.open_input_file(f"{base}/{r['file']}")
            yield r, Page(r["ids"], r["lens"], file.read_at(r["length"], r["offset"]))


# ---- step 1: which minimizers repeat --------------------------------------------------------------------------------


def _ask_minimizers(shards: int, folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r, page in _fetched(folder, batches):
            h, several, _ = page.minimizers()
            order, numbers, heads = _by_shard(h, shards)
            parts = [order[a:z] for a, z in _spans(heads, len(order))]
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(numbers), pa.array([r["page"]] * len(parts)), pa.array([h[p].tobytes() for p in parts], pa.binary()), pa.array([_bits(several[p]) for p in parts], pa.binary())], ["shard", "page", "hashes", "several"])

    return run


def _answer_minimizers(hot_pages: int):
    def run(table: pa.Table) -> pa.Table:
        rows = [np.frombuffer(x, np.uint64) for x in table.column("hashes").to_pylist()]
        lens = [len(x) for x in rows]
        h = np.concatenate(rows)
        several = np.concatenate([_unbits(b, n) for b, n in zip(table.column("several").to_pylist(), lens, strict=True)])
        order = np.argsort(h, kind="stable")
        heads = np.flatnonzero(np.r_[True, h[order][1:] != h[order][:-1]])
        count = np.diff(np.r_[heads, len(h)])
        any_ = np.logical_or.reduceat(several[order], heads)
        shared, hot = np.empty(len(h), bool), np.empty(len(h), bool)
        shared[order] = np.repeat((count > 1) | any_, count)
        hot[order] = np.repeat(count > hot_pages, count)
        cuts = np.cumsum(lens)[:-1]
        return pa.table({
            "page": table.column("page"), "shard": table.column("shard"),
            "shared": pa.array([_bits(x) for x in np.split(shared, cuts)], pa.binary()), "hot": pa.array([_bits(x) for x in np.split(hot, cuts)], pa.binary()),
        })

    return run


# ---- step 2: segments that repeat -----------------------------------------------------------------------------------


def _window_hash(window: bytes) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(window)


class Asked:
    """The segments a page sends, shard by shard, and where they occur in it; the same on every call."""

    def __init__(self, page: Page, answers: list[dict], shards: int):
        h, _, place = page.minimizers()
        order, numbers, heads = _by_shard(h, shards)
        shared, hot = np.zeros(len(h), bool), np.zeros(len(h), bool)
        by = {a["shard"]: a for a in answers}
        for s, (a, z) in zip(numbers.tolist(), _spans(heads, len(order)), strict=True):
            if s in by:
                shared[order[a:z]], hot[order[a:z]] = _unbits(by[s]["shared"], z - a), _unbits(by[s]["hot"], z - a)
        want = np.flatnonzero(shared[place])
        self.lists: dict[int, dict[bytes, int]] = {}
        self.least: dict[int, list[int]] = {}
        self.hashes: dict[int, list[int]] = {}
        self.found: list[tuple[int, int, int, int, int]] = []  # start, stop, document, shard, number in the shard's list
        data, ids = page.data, page.ids
        for a, z, d, m, is_hot, s in zip(
            page.seg_start[want].tolist(), page.seg_stop[want].tolist(), page.seg_doc[want].tolist(), page.seg_hash[want].tolist(), hot[place[want]].tolist(),
            shard_of(page.seg_hash[want], shards).tolist(), strict=True,
        ):
            for p, q in [(i, i + LENGTH) for i in range(a, z - LENGTH + 1)] if is_hot else ((a, z),):
                seg = data[p:q]
                if is_hot:
                    m = _window_hash(seg)
                    s = int(shard_of(np.array([m], np.uint64), shards)[0])
                mine = self.lists.setdefault(s, {})
                number = mine.setdefault(seg, len(mine))
                least = self.least.setdefault(s, [])
                if number == len(least):
                    least.append(int(ids[d]))
                    self.hashes.setdefault(s, []).append(m)
                elif ids[d] < least[number]:
                    least[number] = int(ids[d])
                self.found.append((p, q, d, s, number))


def _ask_segments(shards: int, folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = _pack()
        for r, page in _fetched(folder, batches):
            asked = Asked(page, r["answers"], shards)
            out = [
                (s, r["page"], pack(b"".join(segs)), np.array([len(x) for x in segs], np.uint16).tobytes(), np.array(asked.hashes[s], np.uint64).tobytes(), np.array(asked.least[s], np.int64).tobytes())
                for s, segs in asked.lists.items()
            ]
            if out:
                cols = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), *[pa.array(c, pa.binary()) for c in cols[2:]]], ["shard", "page", "segs", "lens", "hashes", "least"])

    return run


def suffix_order(t: np.ndarray) -> np.ndarray:
    """Order of the suffixes by their first 64 bytes."""
    n = len(t)
    b = np.concatenate([t, np.zeros(8, np.uint8)]).astype(np.uint64)
    for shift in (1, 2, 4):
        b = (b[:-shift] << np.uint64(8 * shift)) | b[shift:]
    key = b[:n]
    step = 8
    while True:
        order = np.argsort(key)
        rank = np.empty(n, np.uint64)
        rank[order] = np.cumsum(np.r_[False, key[order][1:] != key[order][:-1]]).astype(np.uint64) + np.uint64(1)
        if step >= 64 or rank[order[-1]] == n:
            return order
        after = np.zeros(n, np.uint64)
        after[: max(0, n - step)] = rank[step:]
        key = (rank << np.uint64(32)) | after
        step *= 2


def equal_windows(t: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffix order, interval number of each row) of the intervals of rows with ``length`` equal first bytes.

    Interval borders come level by level. Row order[j] of the transform, taken by symbol, is the row from which backward
    extension leads to row j; two neighbours stay in one interval if they extend by the same symbol from one interval.
    """
    order = suffix_order(t)
    bwt = t[order - 1]
    back = np.argsort(bwt, kind="stable").astype(np.int32)
    symbols = bwt[back]
    other = np.r_[True, symbols[1:] != symbols[:-1]]
    interval = np.cumsum(other, dtype=np.int32)
    border, came = np.empty_like(other), np.empty_like(interval)
    for _ in range(1, length):
        np.take(interval, back, out=came, mode="clip")
        border[0] = True
        np.not_equal(came[1:], came[:-1], out=border[1:])
        border |= other
        new = np.cumsum(border, dtype=np.int32)
        if new[-1] == interval[-1]:
            # no interval was divided: no common prefix has just this value, and none has a larger one
            return order, new
        interval = new
    return order, interval


def _answer_segments(table: pa.Table) -> pa.Table:
    merged: dict[bytes, int] = {}
    least: list[int] = []
    minimizer: list[int] = []
    rows = []
    for segs, lens, hashes, mins in zip(*(table.column(c).to_pylist() for c in ("segs", "lens", "hashes", "least")), strict=True):
        data, n, m = _unpack(segs), np.frombuffer(lens, np.uint16).astype(np.int64), np.frombuffer(mins, np.int64)
        stops = np.cumsum(n)
        numbers = []
        for a, z, h, d in zip((stops - n).tolist(), stops.tolist(), np.frombuffer(hashes, np.uint64).tolist(), m.tolist(), strict=True):
            seg = data[a:z]
            i = merged.setdefault(seg, len(merged))
            if i == len(least):
                least.append(d), minimizer.append(h)
            elif d < least[i]:
                least[i] = d
            numbers.append(i)
        rows.append((np.array(numbers), m))
    mins_ = np.array(least, np.int64)
    lens_ = np.fromiter(map(len, merged), np.int64, len(merged))
    windows = lens_ - LENGTH + 1
    first = np.cumsum(windows) - windows
    best = np.repeat(mins_, windows)
    _, place, count = np.unique(np.array(minimizer, np.uint64), return_inverse=True, return_counts=True)
    many = np.flatnonzero(count[place] > 1)
    if len(many):
        keys = list(merged)
        text = np.frombuffer(b"\xff".join([keys[i] for i in many]) + b"\xff", np.uint8)  # 255 stands in no UTF-8 text
        seg_at = np.cumsum(lens_[many] + 1) - lens_[many] - 1
        window_at = np.full(len(text), -1, np.int64)
        for_windows = np.repeat(seg_at - (np.cumsum(windows[many]) - windows[many]), windows[many]) + np.arange(windows[many].sum())
        window_at[for_windows] = np.repeat(first[many] - (np.cumsum(windows[many]) - windows[many]), windows[many]) + np.arange(windows[many].sum())
        order, interval = equal_windows(text, LENGTH)
        real = window_at[order] >= 0
        rows_at, groups = window_at[order][real], interval[real]
        heads = np.flatnonzero(np.r_[True, groups[1:] != groups[:-1]])
        small = np.minimum.reduceat(best[rows_at], heads)
        best[rows_at] = np.repeat(small, np.diff(np.r_[heads, len(groups)]))
    out = []
    for numbers, m in rows:
        w = windows[numbers]
        at = np.repeat(first[numbers] - (np.cumsum(w) - w), w) + np.arange(w.sum())
        out.append(_bits(best[at] < np.repeat(m, w)))
    return pa.table({"page": table.column("page"), "shard": table.column("shard"), "earlier": pa.array(out, pa.binary())})


# ---- step 3: what goes ----------------------------------------------------------------------------------------------


def covered(page: Page, asked: Asked, answers: dict[int, bytes]) -> np.ndarray:
    """A flag for each byte of the page: it goes."""
    size = len(page.data)
    step = np.zeros(size + 1, np.int32)
    if not asked.found:
        return step[:-1] > 0
    start, stop, doc, shard, number = np.array(asked.found, np.int64).T
    # the answers of all shards end to end: where each listed segment's windows begin in them
    shards = sorted(asked.lists)
    windows = [np.fromiter((len(x) - LENGTH + 1 for x in asked.lists[s]), np.int64, len(asked.lists[s])) for s in shards]
    earlier = np.concatenate([_unbits(answers[s], int(n.sum())) for s, n in zip(shards, windows, strict=True)])
    first = np.cumsum(np.concatenate(windows)) - np.concatenate(windows)
    listed = np.zeros(max(shards) + 1, np.int64)
    listed[shards] = np.cumsum([0, *map(len, windows[:-1])])
    segment = listed[shard] + number
    least = np.concatenate([np.array(asked.least[s], np.int64) for s in shards])[segment]
    whole = page.ids[doc] > least
    np.add.at(step, start[whole], 1)
    np.add.at(step, stop[whole], -1)
    start, n, at = start[~whole], (stop - start)[~whole] - LENGTH + 1, first[segment][~whole]
    if len(n):
        inside = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        on = (np.repeat(start, n) + inside)[earlier[np.repeat(at, n) + inside]]
        np.add.at(step, on, 1)
        np.add.at(step, on + LENGTH, -1)
    return np.cumsum(step[:-1]) > 0


OUT = "doc_id long, n_bytes long, n_removed long, spans array<struct<start:long,stop:long>>, kept binary"


def _mark(shards: int, folder: str):
    span = pa.struct([("start", pa.int64()), ("stop", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r, page in _fetched(folder, batches):
            gone = np.zeros(len(page.data), bool)
            if r["earlier"]:
                gone = covered(page, Asked(page, r["answers"], shards), {x["shard"]: x["earlier"] for x in r["earlier"]})
            n, removed, spans, kept = [], [], [], []
            for a, z in zip(page.starts.tolist(), page.stops.tolist(), strict=True):
                flags = gone[a:z]
                edge = np.flatnonzero(np.diff(np.r_[False, flags, False]))
                n.append(z - a), removed.append(int(flags.sum()))
                spans.append([{"start": x, "stop": y} for x, y in edge.reshape(-1, 2).tolist()])
                kept.append(page.bytes[a:z][~flags].tobytes())
            ids = [None if i == NULL_ID else i for i in page.ids.tolist()]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, pa.list_(span)), pa.array(kept, pa.binary())], ["doc_id", "n_bytes", "n_removed", "spans", "kept"])

    return run


def _dealt(index: DataFrame, n_pages: int) -> DataFrame:
    """The index over enough tasks: its rows are small, the pages they stand for are not."""
    return index.repartition(max(index.sparkSession.sparkContext.defaultParallelism, -(-n_pages // PAGES_A_TASK)), "page")


def _by_task(asked: DataFrame, shards: int):
    """The questions grouped by shard, each shard in a task of its own: a task's share does not grow with the input."""
    return asked.withColumn("task", F.col("shard").cast("int")).repartitionById(shards, "task").groupBy("task", "shard")


def _shared_minimizers(index: DataFrame, folder: str, shards: int, hot_pages: int) -> DataFrame:
    asked = index.mapInArrow(_ask_minimizers(shards, folder), "shard long, page long, hashes binary, several binary")
    answer = _by_task(asked, shards).applyInArrow(_answer_minimizers(hot_pages), "page long, shard long, shared binary, hot binary")
    return written(answer.groupBy("page").agg(F.collect_list(F.struct("shard", "shared", "hot")).alias("answers")), "answers")


def _earlier_windows(index: DataFrame, folder: str, shards: int) -> DataFrame:
    asked = index.mapInArrow(_ask_segments(shards, folder), "shard long, page long, segs binary, lens binary, hashes binary, least binary")
    earlier = _by_task(asked, shards).applyInArrow(_answer_segments, "page long, shard long, earlier binary")
    return written(earlier.groupBy("page").agg(F.collect_list(F.struct("shard", "earlier")).alias("earlier")), "earlier")


def remove_repeats(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shard_bytes: int = SHARD_BYTES, hot_pages: int = HOT_PAGES) -> DataFrame:
    """(doc_id, n_bytes, n_removed, spans, kept) for each document; kept holds the bytes that stay."""
    spark = docs.sparkSession
    folder = fresh_path(spark, "pages")
    index = written(pages_of(docs, folder, id_col, text_col), "page-index")
    n_pages, total = index.agg(F.count(F.lit(1)), F.coalesce(F.sum("n_bytes"), F.lit(0))).first()
    shards = max(2 * spark.sparkContext.defaultParallelism, -(-total // shard_bytes))
    answer = _shared_minimizers(_dealt(index, n_pages), folder, shards, hot_pages)
    release(spark)
    index = index.join(answer, "page", "left").withColumn("answers", F.coalesce("answers", F.array()))
    earlier = _earlier_windows(_dealt(index, n_pages), folder, shards)
    release(spark)
    index = index.join(earlier, "page", "left").withColumn("earlier", F.coalesce("earlier", F.array()))
    return _dealt(index, n_pages).mapInArrow(_mark(shards, folder), OUT)


SQL = """
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, hex(encode(coalesce(text, ''))) AS h, CAST(strlen(coalesce(text, '')) AS BIGINT) AS n FROM documents),
w AS (SELECT rid, doc_id, p, md5(substr(h, 2 * p + 1, 100)) AS k FROM (SELECT rid, doc_id, h, unnest(range(0, greatest(n - 49, 0))) AS p FROM d)),
f AS (SELECT k, min(doc_id) AS first FROM w GROUP BY k),
hit AS (SELECT rid, p FROM w JOIN f USING (k) WHERE first < doc_id),
s AS (SELECT rid, p, CASE WHEN p <= lag(p) OVER (PARTITION BY rid ORDER BY p) + 50 THEN 0 ELSE 1 END AS new FROM hit),
g AS (SELECT rid, min(p) AS a, max(p) + 50 AS b FROM (SELECT rid, p, sum(new) OVER (PARTITION BY rid ORDER BY p) AS run FROM s) GROUP BY rid, run),
c AS (SELECT rid, count(*) AS n_spans, CAST(sum(b - a) AS BIGINT) AS n_removed FROM g GROUP BY rid),
gap AS (SELECT rid, coalesce(lag(b) OVER (PARTITION BY rid ORDER BY a), 0) AS x, a AS y FROM g UNION ALL SELECT rid, coalesce(max(b), 0), max(n) FROM d LEFT JOIN g USING (rid) GROUP BY rid),
kept AS (SELECT rid, string_agg(substr(h, 2 * x + 1, 2 * (y - x)), '' ORDER BY x) AS k FROM gap JOIN d USING (rid) GROUP BY rid)
SELECT doc_id, n AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(k)) AS kept_sha256 FROM d JOIN kept USING (rid) LEFT JOIN c USING (rid)
"""
