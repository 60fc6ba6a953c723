"""Random walks of first and second order."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .checkpoints import settle
from .config import WalkConfig
from .graph import degrees
from .randomness import SPAN, draw, fast_draw, numpy_draw

#: Neighbours in one adjacency row; a hub has several.
CHUNK = 4096
#: Largest adjacency, in MB, that is sent to the executors instead of joined.
BROADCAST_MB = 64.0
HOPS_BEFORE_WRITE = 8


def chunked(edges: DataFrame, weighted: bool = True, chunk: int = CHUNK) -> DataFrame:
    """(node, chunk, dst, w): the neighbours of each node dealt into chunks of about `chunk` by hash, so that no task and no
    row holds all of a hub's."""
    w = F.col("weight") if weighted else F.lit(1.0)
    parts = settle(degrees(edges).select("node", F.ceil(F.col("degree") / chunk).alias("parts")), "parts")
    e = edges.select(F.col("src").alias("node"), "dst", w.alias("w")).join(parts, "node")
    return e.select("node", F.when(F.col("parts") > 1, F.pmod(F.xxhash64("dst"), F.col("parts"))).otherwise(0).cast("int").alias("chunk"), "dst", "w")


def adjacency(edges: DataFrame, weighted: bool = True, chunk: int = CHUNK) -> tuple[DataFrame, DataFrame]:
    """heads(node, total, tops) and chunks(node, chunk, nbrs, cum): running weights along the sorted neighbours of a chunk.

    tops holds the running weight at the end of each chunk, so a draw finds its chunk and then its neighbour.
    """
    own = Window.partitionBy("node", "chunk").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0)
    d = chunked(edges, weighted, chunk).withColumn("c", F.sum("w").over(own))
    listed = d.groupBy("node", "chunk").agg(F.sort_array(F.collect_list(F.struct("dst", "c"))).alias("l"))
    chunks = settle(listed.select("node", "chunk", F.col("l.dst").alias("nbrs"), F.col("l.c").alias("cum")), "chunks")
    # one row a chunk; a node without one of its numbers has none there, so the chunks are numbered anew by the list's places
    heads = chunks.groupBy("node").agg(F.sort_array(F.collect_list(F.struct("chunk", F.element_at("cum", -1).alias("t")))).alias("l"))
    tops = F.expr("aggregate(l, named_struct('a', CAST(array() AS ARRAY<DOUBLE>), 't', CAST(0 AS DOUBLE)), (s, x) -> named_struct('a', concat(s.a, array(s.t + x.t)), 't', s.t + x.t)).a")
    return heads.select("node", tops.alias("tops"), F.col("l.chunk").alias("numbers")).select("node", F.element_at("tops", -1).alias("total"), "tops", "numbers"), chunks


def stepped(front: DataFrame, heads: DataFrame, chunks: DataFrame, at: Column, out: str) -> DataFrame:
    """front(cur, ...) with the neighbour of cur whose running weight is the first above `at` (of the total) as out. Rows
    whose cur has no neighbour go."""
    f = front.join(heads.withColumnRenamed("node", "cur"), "cur").withColumn("u", at)
    f = f.withColumn("at", _chosen(F.col("u"), "tops"))
    f = f.withColumns({"u": F.expr("u - IF(at = 0, 0D, tops[greatest(at, 1) - 1])"), "chunk": F.expr("numbers[at]")}).drop("total", "tops", "numbers", "at")
    f = f.join(chunks.withColumnRenamed("node", "cur"), ["cur", "chunk"])
    return f.withColumn(out, F.expr("nbrs[least(size(filter(cum, c -> c <= u)), size(cum) - 1)]")).drop("nbrs", "cum", "u", "chunk")


def starts(edges: DataFrame, cfg: WalkConfig) -> DataFrame:
    """(walk_id, cur): per_node walks from each node, or as many in all, spread by strength ('stationary')."""
    d = degrees(edges)
    if cfg.start == "uniform":
        return d.select(F.col("node").alias("cur"), F.explode(F.expr(f"sequence(0, {cfg.per_node - 1})")).alias("i")).select((F.col("cur") * cfg.per_node + F.col("i")).alias("walk_id"), "cur")
    n, total = d.agg(F.count("*"), F.sum("strength")).first()
    if not n:
        return d.select(F.col("node").alias("walk_id"), F.col("node").alias("cur"))
    share = F.col("strength") * float(n * cfg.per_node / total)
    count = F.floor(share) + (fast_draw(cfg.seed, F.lit("start"), F.col("node")) / F.lit(float(SPAN)) < share - F.floor(share)).cast("int")
    spread = d.select("node", count.cast("int").alias("n")).filter("n > 0")
    # ids stay apart: no node has more walks than 2^20
    spread = spread.select(F.col("node").alias("cur"), F.explode(F.expr("sequence(0, n - 1)")).alias("i"))
    return spread.select((F.col("cur") * (1 << 20) + F.col("i")).alias("walk_id"), "cur")


def _chosen(u: Column, cum: str) -> Column:
    """Number of the first running weight above u."""
    return F.least(F.size(F.filter(cum, lambda c: c <= u)), F.size(cum) - 1)


def sample_walks(edges: DataFrame, cfg: WalkConfig = WalkConfig(), weighted: bool = True, oracle: bool = False, mode: str = "auto", broadcast_mb: float = BROADCAST_MB) -> DataFrame:
    """walks(walk_id, path). A step is a function of (seed, walk_id, position), so no plan changes the walks. On edges that
    are not symmetric, a walk that meets a node without a way on is left out.

    mode 'hops' joins the walks' ends with the adjacency for each step; 'broadcast' sends an adjacency of checked size to
    the executors and walks in one pass; 'auto' decides by that size. oracle draws by md5, for hops alone.
    """
    front = starts(edges, cfg).withColumn("path", F.array("cur"))
    small = mode == "broadcast" or mode == "auto" and not oracle and edges.count() * 24 / 1e6 <= broadcast_mb
    if small and not oracle:
        return _broadcast_walks(edges, front.drop("path"), cfg, weighted)
    heads, chunks = adjacency(edges, weighted)
    heads = settle(heads, "heads")
    source = draw if oracle else fast_draw
    for at in range(1, cfg.walk_length):
        u = source(cfg.seed, F.col("walk_id"), F.lit(at).cast("long")) / F.lit(float(SPAN)) * F.col("total")
        f = stepped(front, heads, chunks, u, "next")
        front = f.select("walk_id", F.col("next").alias("cur"), F.concat("path", F.array("next")).alias("path"))
        if at % HOPS_BEFORE_WRITE == 0:
            front = settle(front, "walks")
    return front.select("walk_id", "path")


def _broadcast_walks(edges: DataFrame, front: DataFrame, cfg: WalkConfig, weighted: bool) -> DataFrame:
    rows = chunked(edges, weighted).orderBy("node", "chunk", "dst").select("node", "dst", "w").toArrow()
    src, dst, w = (rows.column(i).to_numpy() for i in range(3))
    node, first = np.unique(src, return_index=True)
    last = np.append(first[1:], len(src))
    cum = np.cumsum(w) - np.repeat(np.concatenate([[0.0], np.cumsum(w)])[first], last - first) if len(src) else w
    sent = edges.sparkSession.sparkContext.broadcast((node, first, last, dst, cum))
    length, seed = cfg.walk_length, cfg.seed

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        node, first, last, dst, cum = sent.value
        for batch in batches:
            walk, cur = (batch.column(i).to_numpy() for i in range(2))
            path = np.empty((len(walk), length), np.int64)
            path[:, 0] = cur
            alive = np.ones(len(walk), bool)
            if not len(node):
                continue
            for at in range(1, length):
                i = np.minimum(np.searchsorted(node, cur), len(node) - 1)
                alive &= node[i] == cur
                u = numpy_draw(seed, walk, at) / float(SPAN) * cum[last[i] - 1]
                a, b = first[i].copy(), last[i] - 1
                while (a < b).any():  # the first running weight above u, for all walks at once
                    middle = (a + b) // 2
                    above = cum[middle] > u
                    a, b = np.where(above | (a >= b), a, middle + 1), np.where(above, middle, b)
                cur = dst[a]
                path[:, at] = cur
            path = path[alive]
            offsets = np.arange(0, len(path) * length + 1, length, dtype=np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(alive)), pa.ListArray.from_arrays(offsets, path.ravel())], ["walk_id", "path"])

    return front.select("walk_id", "cur").mapInArrow(run, "walk_id long, path array<long>")


def _placed(heads: DataFrame, chunks: DataFrame) -> DataFrame:
    """(node, dst, w, start): each neighbour's weight, and the running weight before it."""
    d = chunks.join(heads.select("node", "tops", F.col("numbers")), "node").withColumn("at", F.array_position("numbers", F.col("chunk")).cast("int"))
    d = d.select("node", F.expr("IF(at = 1, 0D, tops[greatest(at, 2) - 2])").alias("base"), "cum", F.posexplode("nbrs").alias("i", "dst"))
    before = F.expr("IF(i = 0, 0D, cum[greatest(i, 1) - 1])")
    return d.select("node", "dst", (F.expr("cum[i]") - before).alias("w"), (F.col("base") + before).alias("start"))


def sample_walks_biased(edges: DataFrame, cfg: WalkConfig = WalkConfig(), p: float = 1.0, q: float = 1.0, oracle: bool = False, tries: int = 12) -> DataFrame:
    """Second-order walks: a step back weighs 1/p, one to a neighbour of the last node 1, one farther away 1/q, each times
    the edge's weight.

    By rejection, which is exact: a try is the step back with its share of (weight back / p + other weights · m), m the
    larger of 1 and 1/q, and else a first-order step to another node, kept with its own weight over m. Tries are numbered
    and each draws by its number; the first kept one counts, and walks without one go on trying, so no try is ever taken
    unkept. At least min(q, 1/q) of the tries are kept, whatever p is. A step needs the adjacency of the current node and
    look-ups of single edges; no walk carries neighbour lists.
    """
    m = max(1.0, 1 / q)
    source = draw if oracle else fast_draw
    heads, chunks = adjacency(edges)
    heads = settle(heads, "heads")
    known = settle(_placed(heads, chunks), "known")
    totals = heads.select(F.col("node").alias("cur"), F.col("total").alias("all"))
    front = starts(edges, cfg).select("walk_id", F.lit(None).cast("long").alias("last"), "cur", F.array("cur").alias("path"))
    share = lambda name, at: source(cfg.seed, F.lit(name), F.col("walk_id"), F.lit(at).cast("long"), F.col("try")) / F.lit(float(SPAN))
    for at in range(1, cfg.walk_length):
        back = known.select(F.col("node").alias("cur"), F.col("dst").alias("last"), F.col("w").alias("back"), "start")
        left = front.join(totals, "cur").join(back, ["cur", "last"], "left").fillna(0.0, ["back"])
        done, first, more = None, 0, tries
        while True:
            f = left.withColumn("try", F.explode(F.expr(f"sequence({first}, {first + more - 1})")))
            others = F.col("all") - F.col("back")
            f = f.withColumn("returns", share("back", at) * (F.col("back") / p + others * m) < F.col("back") / p)
            f = f.withColumn("x", share("step", at) * others)
            # the last node's own stretch of the running weights is passed over
            f = stepped(f, heads, chunks, F.when(F.col("x") >= F.col("start"), F.col("x") + F.col("back")).otherwise(F.col("x")), "cand")
            near = known.select(F.col("node").alias("last"), F.col("dst").alias("cand"), F.lit(True).alias("near"))
            f = f.join(near, ["last", "cand"], "left")
            weight = F.when(F.col("last").isNull(), F.lit(m)).when(F.col("cand") == F.col("last"), F.lit(0.0)).when(F.col("near"), F.lit(1.0)).otherwise(F.lit(1 / q))
            f = f.withColumn("next", F.when(F.col("returns"), F.col("last")).when(share("keep", at) * m < weight, F.col("cand")))
            got = settle(f.filter("next IS NOT NULL").groupBy("walk_id").agg(F.min_by("next", "try").alias("next")), "kept")
            done = got if done is None else done.unionByName(got)
            left = left.join(got, "walk_id", "left_anti")
            if left.isEmpty():
                break
            left, first, more = settle(left, "left"), first + more, 4 * tries
        front = front.join(done, "walk_id").select("walk_id", F.col("cur").alias("last"), F.col("next").alias("cur"), F.concat("path", F.array("next")).alias("path"))
        if at % 4 == 0:
            front = settle(front, "biased")
    return front.select("walk_id", "path")
