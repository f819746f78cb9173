"""The window index: for each time that starts something, the events up to the maximum duration after it.

Rows (chunk, own, ts, pos, t, item, u, rest): pos counts events of the window in the order of (t, rank), rest sums the utilities of those after this one.
Times are cut into chunks. A chunk gets its own rows and a halo of two durations after it, in one shuffle by chunk; windows are built inside it. Starts in the halo (own = false) only serve to
decide which own starts are minimal.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Times of a chunk of `arrays_by_set`, and windows that a task of `merged` takes together.
SET_CHUNK, MERGED_ROWS = 4096, 200_000
NAMES = ("ts", "head", "t", "items", "u", "rest", "n")
ARRAYS = "ts long, head int, t array<long>, items array<string>, u array<long>, rest array<long>, n long"
ITEM_ORDERS = ("lexicographic", "utility", "bound")


def gap(mtd: int, span: str) -> int:
    """The largest distance of first and last time."""
    if span not in ("gap", "points"):
        raise ValueError(f"span: {span}")
    return mtd if span == "gap" else mtd - 1


def chunk_length(width: int, chunk_len: int | None) -> int:
    return max(1, chunk_len or max(512, 32 * (width + 1)))


def ranked(ces: DataFrame, order: str, width: int) -> DataFrame:
    """ces with rank, the place of items in the one order of extension: by text, by utility (rising), or by the raw bound (falling)."""
    if order == "lexicographic":
        return ces.withColumn("rank", F.col("item"))
    if order not in ITEM_ORDERS:
        raise ValueError(f"order: {order}")
    if order == "utility":
        items = ces.groupBy("item").agg(F.sum("u").alias("v"))
    else:
        items = one_episode_table(build(ces, width)).select("item", (-F.col("raw")).alias("v"))
    # One row an item: sorted by ranges, numbered by their text form so that no single task orders them all.
    items = items.select("item", F.concat(F.lpad((F.col("v") + (1 << 62)).cast("string"), 20, "0"), F.lit("|"), F.col("item")).alias("rank"))
    return ces.join(items, "item")


def build(ces: DataFrame, width: int, chunk_len: int | None = None, order: str = "lexicographic", from_t: bool = False) -> DataFrame:
    """The index. With from_t also the utilities of all events from this one's time on."""
    size = chunk_length(width, chunk_len)
    rows = ranked(ces, order, width) if order != "lexicographic" else ces.withColumn("rank", F.col("item"))
    chunks = F.sequence(F.floor((F.col("t") - 2 * width) / size), F.floor(F.col("t") / size))
    rows = rows.withColumn("chunk", F.explode(chunks)).repartition("chunk")
    first, last = F.col("chunk") * size, (F.col("chunk") + 1) * size + width
    starts = F.sequence(F.greatest(F.col("t") - width, first), F.least(F.col("t"), last - 1))
    rows = rows.filter(F.greatest(F.col("t") - width, first) <= F.least(F.col("t"), last - 1)).withColumn("ts", F.explode(starts))
    inside = W.partitionBy("chunk", "ts")
    in_order = inside.orderBy("t", "rank")
    rows = rows.withColumns({
        "starts": F.max(F.col("t") == F.col("ts")).over(inside),
        "pos": F.row_number().over(in_order),
        "rest": F.coalesce(F.sum("u").over(in_order.rowsBetween(1, W.unboundedFollowing)), F.lit(0)),
    })
    rows = rows.filter("starts").withColumn("own", F.col("ts") < (F.col("chunk") + 1) * size)
    if from_t:
        rows = rows.withColumn("from_t", F.sum("u").over(inside.orderBy("t").rangeBetween(W.currentRow, W.unboundedFollowing)))
    return rows.select("chunk", "own", "ts", "pos", "t", "item", "u", "rest", *(["from_t"] if from_t else []))


def arrays(windows: DataFrame) -> DataFrame:
    """(ts, head, t[], items[], u[], rest[], n = 1): one row a start; head is the number of events at the start itself."""
    rows = windows.filter("own").groupBy("ts").agg(F.array_sort(F.collect_list(F.struct("pos", "t", "item", "u", "rest"))).alias("w"))
    head = F.size(F.filter("w", lambda x: x["t"] == F.col("ts")))
    return rows.select("ts", head.alias("head"), F.col("w.t").alias("t"), F.col("w.item").alias("items"), F.col("w.u").alias("u"), F.col("w.rest").alias("rest"), F.lit(1).cast("long").alias("n"))


def arrays_by_set(ces: DataFrame, width: int, chunk_len: int = SET_CHUNK) -> DataFrame:
    """`arrays(build(ces, width))` in the lexicographic order, from one row an event instead of one an event and start: each chunk's windows are cut out of its sorted events by binary search."""
    chunks = F.sequence(F.floor((F.col("t") - width) / chunk_len), F.floor(F.col("t") / chunk_len))
    rows = ces.select("t", "item", "u", F.explode(chunks).alias("chunk")).repartition("chunk")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _sorted(batches)
        if not table.num_rows:
            return
        t, u, chunk = (table[c].to_numpy() for c in ("t", "u", "chunk"))
        item = table["item"].combine_chunks()
        for begin in np.flatnonzero(np.r_[True, chunk[1:] != chunk[:-1]]).tolist():
            end = int(np.searchsorted(chunk, chunk[begin], "right"))
            yield _windows(t[begin:end], item.slice(begin, end - begin), u[begin:end], width, (int(chunk[begin]) + 1) * chunk_len, int(chunk[begin]) * chunk_len)

    return rows.mapInArrow(cut, ARRAYS)


def _sorted(batches: Iterator[pa.RecordBatch]) -> pa.Table:
    """The events of some chunks by chunk, time and item."""
    table = pa.Table.from_batches(batches := list(batches)) if batches else pa.table({"t": []})
    return table.sort_by([("chunk", "ascending"), ("t", "ascending"), ("item", "ascending")]) if table.num_rows else table


def _windows(t: np.ndarray, item: pa.Array, u: np.ndarray, width: int, end: int, begin: int) -> pa.RecordBatch:
    """The windows that start from begin on and before end, of sorted events."""
    ts = np.unique(t[(t >= begin) & (t < end)])
    low, high = np.searchsorted(t, ts), np.searchsorted(t, ts + width, "right")
    sizes, head = high - low, np.searchsorted(t, ts, "right") - low
    offsets = np.r_[0, sizes.cumsum()]
    at = np.arange(offsets[-1]) + np.repeat(low - offsets[:-1], sizes)
    until = np.r_[0, u.cumsum()]
    rest = np.repeat(until[high], sizes) - until[at + 1]
    lists = lambda values: pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), values)
    return pa.RecordBatch.from_arrays([pa.array(ts), pa.array(head, pa.int32()), lists(pa.array(t[at])), lists(item.take(pa.array(at))), lists(pa.array(u[at])), lists(pa.array(rest)), pa.array(np.ones(len(ts), np.int64))], names=list(NAMES))


def merged(index: DataFrame) -> DataFrame:
    """The index with one row for all windows of the same items at the same distances from their starts: n of them, with the sums of u and rest, at the first one's times.

    Whether an occurrence from a window's start is minimal shows inside the window, and all values of episodes are sums over windows, so that no result depends on it."""
    alike = index.select(*NAMES).repartition(F.transform("t", lambda x: x - F.col("ts")), "items")

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The rows of a partition, as many at a time as come, and what they make with those before."""
        so_far, waiting = [], 0
        for batch in batches:
            so_far.append(batch)
            waiting += batch.num_rows
            if waiting > MERGED_ROWS:
                so_far, waiting = [_alike(pa.Table.from_batches(so_far))], 0
        if so_far:
            yield _alike(pa.Table.from_batches(so_far))

    return alike.mapInArrow(merge, ARRAYS)


def _alike(table: pa.Table) -> pa.RecordBatch:
    """One row for each different window of a table."""
    table = table.combine_chunks()
    ts, n = table["ts"].to_numpy(), table["n"].to_numpy()
    columns = {c: events(table[c]) for c in ("t", "items", "u")}
    offsets, t = columns["t"]
    sizes, u = np.diff(offsets), columns["u"][1].to_numpy()
    row = np.repeat(np.arange(len(ts)), sizes)
    names = columns["items"][1].dictionary_encode()
    code = np.stack([t.to_numpy() - ts[row], names.indices.to_numpy().astype(np.int64)], axis=1)
    place = np.arange(len(row)) - offsets[row]
    first, same = np.zeros(0, np.int64), np.zeros(len(ts), np.int64)
    for size in np.unique(sizes).tolist():  # windows of as many events
        mine = np.flatnonzero(sizes == size)
        mine = mine[np.argsort(ts[mine], kind="stable")]
        keys = code[(offsets[mine][:, None] + np.arange(size)).ravel()].reshape(len(mine), 2 * size)
        _, at, inverse = np.unique(keys.view(np.dtype((np.void, 16 * size))).ravel(), return_index=True, return_inverse=True)
        same[mine], first = inverse.ravel() + len(first), np.r_[first, mine[at]]
    number = np.zeros(len(first), np.int64)
    np.add.at(number, same, n)
    begin = np.r_[0, sizes[first].cumsum()]
    total = np.zeros(begin[-1], np.int64)
    np.add.at(total, begin[same[row]] + place, u)
    until = np.r_[0, total.cumsum()]
    rest = np.repeat(until[begin[1:]], sizes[first]) - until[1:]
    at = np.arange(begin[-1]) + np.repeat(offsets[first] - begin[:-1], sizes[first])
    lists = lambda values: pa.ListArray.from_arrays(pa.array(begin, pa.int32()), values)
    kept = pa.array(at)
    return pa.RecordBatch.from_arrays([pa.array(ts[first]), table["head"].combine_chunks().take(pa.array(first)), lists(t.take(kept)), lists(columns["items"][1].take(kept)), lists(pa.array(total)), lists(pa.array(rest)), pa.array(number)], names=list(NAMES))


def events(column: pa.ChunkedArray) -> tuple[np.ndarray, pa.Array]:
    """Where each row's list begins (and the last ends), and the entries of all lists."""
    whole = column.combine_chunks()
    offsets = whole.offsets.to_numpy().astype(np.int64)
    return offsets - offsets[0], whole.flatten()


def episodes_at_starts(index: DataFrame) -> DataFrame:
    """`one_episode_table` from arrays of windows, merged or not, with the number of rows as starts."""
    at = lambda c: F.element_at(c, F.col("p"))
    rows = index.select("n", (F.col("u")[0] + F.col("rest")[0]).alias("all"), F.explode(F.sequence(F.lit(1), "head")).alias("p"), "items", "u", "rest")
    rows = rows.select("n", "all", at("items").alias("item"), at("u").alias("u"), at("rest").alias("rest"))
    return rows.groupBy("item").agg(
        F.count("*").alias("starts"),
        F.sum("n").alias("frequency"),
        F.sum("u").cast("long").alias("utility"),
        F.sum(F.col("u") + F.col("all")).cast("long").alias("raw"),
        F.sum("all").cast("long").alias("no_overlap"),
        F.sum(F.col("u") + F.col("rest")).cast("long").alias("remaining"),
    )


def one_episode_table(windows: DataFrame) -> DataFrame:
    """(item, frequency, utility, raw, no_overlap, remaining) of episodes of one event, each bound a sum over its occurrences."""
    inside = W.partitionBy("chunk", "ts")
    rows = windows.filter("own").withColumn("all", F.sum("u").over(inside)).filter(F.col("t") == F.col("ts"))
    return rows.groupBy("item").agg(
        F.count("*").alias("frequency"),
        F.sum("u").cast("long").alias("utility"),
        F.sum(F.col("u") + F.col("all")).cast("long").alias("raw"),
        F.sum("all").cast("long").alias("no_overlap"),
        F.sum(F.col("u") + F.col("rest")).cast("long").alias("remaining"),
    )
