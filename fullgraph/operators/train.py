"""Synchronous full-batch training over a partitioned graph.

A part of the graph is its nodes' arrays and edge lists.  An epoch is one Spark
job of ``2 L + 1`` supersteps; in a superstep every part absorbs the messages
sent to it and sends the next ones.  A message is one record per ordered pair of
parts: raw source vectors (post) and partial sums (pre) going forward, and the
gradients of both going back over the same cover, as the bytes of
:func:`quantize.to_message`.  Parameters are small and live on the driver; each
part returns one record of gradients.

Only messages are exchanged.  Parts are dealt to their tasks once and persisted;
what a part keeps from one superstep to the next (its activations) is persisted
where it was computed.  Both meet the messages in a union of equally partitioned
data sets, which needs no exchange.  The table API has no such step: the output
of a grouped pass counts as unpartitioned, so a part's state would be shuffled
with its messages at every superstep.  That is why this module, and only this
one, works on records (RDDs) below the table of parts.

Nothing is kept between epochs but the parameters (and, for the delayed
baselines, checkpointed remote sums), so lineage does not grow and a lost
executor costs at most the running epoch: its parts are read again from the
table of parts.
"""

from __future__ import annotations

import math
import pickle
import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from itertools import groupby

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import checkpoint_root, cut, drop, ship, traffic
from ..sources.graphs import Graph
from . import layers, remote
from .cover import MAX_PAIR_EDGES, groups, konig_cover
from .propagate import shown_rows
from .quantize import from_message, to_message

SPLITS = ("train", "val", "test")
COMBINE_OVER = 64
#: Bytes of one record of a part's arrays; a part may have many.  A row group has 100 records at least,
#: and is in memory whole where it is written or read.
CHUNK = 1 << 19
#: Bytes of the states of models that share passes, in one part: a task holds them beside the part itself.
SHARED_STATE = 96 << 20


@dataclass(frozen=True)
class TrainConfig:
    layers: int = 3
    hidden: int = 16
    lr: float = 0.01
    epochs: int = 10
    dropout: float = 0.5
    model: str = "sage"  # sage, gcn, gin
    route: str = "hybrid"  # edge, pre, post, hybrid, best_of_two, approx_cover
    bits: int = 32
    rounding: str = "stochastic"
    group_rows: int = 1
    adaptive: bool = False  # bits per message from the spread of its rows: 2, 4 or 8
    adaptive_error: float = 1.0  # the step between codes that it allows, in mean absolute values
    q_forward: bool = True
    q_backward: bool = True
    layer_norm: bool = True
    lp: bool = True
    lp_rate: float = 0.5
    refresh_every: int = 1  # remote sums are exchanged every so many epochs
    stale_lag: int = 0  # 1: an epoch uses the sums that the epoch before received
    boundary_rate: float = 1.0
    optimizer: str = "adam"
    seed: int = 0


#: Records stay as the bytes that Python wrote: PySpark's other levels compress a part's arrays again for every superstep.
KEPT = StorageLevel.MEMORY_AND_DISK_DESER


def _home(part: int) -> int:
    return part


def _sent(records: RDD, parts: int) -> RDD:
    """Records dealt to the task of their part.

    A dealt data set names another serializer than a mapped one, though both are streams of pickled lists;
    under one name, a union takes them as they are and needs no pass that writes them again.
    """
    dealt = records.partitionBy(parts, _home)
    return RDD(dealt._jrdd, dealt.ctx, dealt.ctx.serializer)


def _shuffle_of(dealt: RDD) -> int:
    """The number of the shuffle that :func:`_sent` made."""
    rdd = dealt._jrdd.rdd()
    while rdd.getClass().getSimpleName() != "ShuffledRDD":
        rdd = rdd.dependencies().head().rdd()
    return rdd.dependencies().head().shuffleId()


@dataclass
class Prepared:
    """The graph as a table of parts, and its sizes."""

    table: DataFrame
    parts: int
    width: int
    classes: int
    nodes: int = 0
    _dealt: RDD | None = None

    def dealt(self) -> RDD:
        """The parts' records, each part in a task of its own; dealt and persisted once."""
        if self._dealt is None:
            rows = self.table.rdd.map(lambda r: (r.part, ("part", r.seq, bytes(r.payload))))
            self._dealt = _sent(rows, self.parts).persist(KEPT)
        return self._dealt

    def release(self) -> None:
        if self._dealt is not None:
            self._dealt.unpersist()
            self._dealt = None


@dataclass
class Result:
    params: dict[str, np.ndarray]
    history: list[dict] = field(default_factory=list)
    sent_bytes: int = 0
    param_bytes: int = 0
    shuffle_bytes: int = 0


# ---------------------------------------------------------------- building the part rows


def _small(v: np.ndarray) -> np.ndarray:
    """Places as 32-bit numbers where they fit."""
    return v.astype(np.int32) if not len(v) or v.max() < 1 << 31 else v


def _segments(key: np.ndarray, other: np.ndarray, w: np.ndarray | None) -> tuple:
    """Edges clustered by ``key``: (distinct keys, run starts, other ends, weights or None where all are one)."""
    if w is None or (w == 1).all():
        w, span = None, int(other.max()) + 1 if len(other) else 1
        key, other = np.divmod(np.sort(key.astype(np.int64) * span + other), span)
    else:
        order = np.lexsort((other, key))
        key, other, w = key[order], other[order], w[order]
    first = np.concatenate([[True], key[1:] != key[:-1]]) if len(key) else np.zeros(0, dtype=bool)
    return _small(key[first]), _small(np.flatnonzero(first)), _small(other), w


def _split_codes(split) -> np.ndarray:
    return np.array([SPLITS.index(v) if v in SPLITS else -1 for v in split.to_pylist()], dtype=np.int64)


def _arranged(part: int, ids: np.ndarray, x: np.ndarray, y: np.ndarray, s: np.ndarray, here: tuple, send: Iterator[tuple[int, tuple]], recv: Iterator[tuple[int, tuple]]) -> dict:
    """A part's arrays from its nodes, its local edges (a, b, w) and those to and from each other part (a, b, w, post).

    ``w`` None is one everywhere; ``post`` None is a row per edge.
    """
    order = np.argsort(ids, kind="stable")
    ids, x, y, s = ids[order], x[order], y[order], s[order]
    at = lambda v: np.searchsorted(ids, v)
    some = lambda w, rows: None if w is None else w[rows]
    a, b, w = here
    src, dst = at(a), at(b)
    deg = np.bincount(dst, minlength=len(ids)).astype(float)
    out = {"part": part, "ids": ids, "x": x, "y": y, "split": s, "here": _segments(dst, src, w), "here_t": _segments(src, dst, w), "send": {}, "recv": {}}
    for name, pairs in (("send", send), ("recv", recv)):
        for other, (a, b, w, post) in pairs:
            if post is None:  # a row per edge, in an order that both ends know
                order = np.lexsort((a, b))
                a, b, w, post = a[order], b[order], some(w, order), np.zeros(len(a), dtype=bool)
                sources, targets, row = a[:0], b, np.arange(len(b))
            else:
                sources, targets = np.unique(a[post]), np.unique(b[~post])
                row = np.searchsorted(targets, b[~post])
            if name == "send":
                pre, w = at(a[~post]), some(w, ~post)
                out[name][other] = {"post": _small(at(sources)), "pre": _segments(row, pre, w), "pre_t": _segments(pre, row, w), "n_pre": len(targets)}
            else:
                deg += np.bincount(at(b), minlength=len(ids))
                to, by, w = at(b[post]), np.searchsorted(sources, a[post]), some(w, post)
                out[name][other] = {"post": _segments(to, by, w), "post_t": _segments(by, to, w), "n_post": len(sources), "pre": _small(at(targets))}
    out["deg"] = deg
    return out


#: Edges of one packed record: an Arrow batch has 10,000 records, which stay below half a gigabyte.
PACK = 2048
#: Edges that a task gathers before it packs them by pair of parts.
GATHER = 1 << 20
PACKED = "part int, kind int, other int, a binary, b binary, w binary, mark binary"
#: Marks of an edge by its route; a local one has none.
MARKS = {"pre": 0, "post": 1, "edge": 2}


def _records(rows: list[tuple]) -> pa.RecordBatch:
    types = [pa.int32()] * 3 + [pa.binary()] * 4
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=["part", "kind", "other", "a", "b", "w", "mark"])


def _pack_nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (part, id, feat, label, split) to packed records of kind 0: ids, features, labels and splits."""
    for batch in batches:
        part = np.asarray(batch.column(0))
        rows = []
        for p in np.unique(part).tolist():
            t = batch.filter(pa.array(part == p))
            x = np.asarray(t.column(2).flatten(), dtype=np.float64)
            y = t.column(3).fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
            rows.append((p, 0, None, np.asarray(t.column(1)).astype(np.int64).tobytes(), x.tobytes(), y.tobytes(), _split_codes(t.column(4)).tobytes()))
        if rows:
            yield _records(rows)


def _by_pair(batches: Iterator[pa.RecordBatch], columns: tuple[str, ...]) -> Iterator[tuple[int, int, list[np.ndarray]]]:
    """(sp, dp, arrays of ``columns``), at most ``PACK`` edges of a pair at a time, about ``GATHER`` rows taken together."""

    def cut_up(held: list[pa.RecordBatch]) -> Iterator[tuple[int, int, list[np.ndarray]]]:
        t = pa.Table.from_batches(held)
        sp, dp = (t[c].to_numpy() for c in ("sp", "dp"))
        cols = [_marks(t[c]) if c == "route" else t[c].to_numpy() for c in columns]
        if len(sp) and 0 <= min(sp.min(), dp.min()) and max(sp.max(), dp.max()) < 256:  # 16 bits: a radix sort
            order = np.argsort((sp * 256 + dp).astype(np.uint16), kind="stable")
        else:
            order = np.lexsort((dp, sp))
        sp, dp, cols = sp[order], dp[order], [c[order] for c in cols]
        begin = np.flatnonzero(np.concatenate([[True], (sp[1:] != sp[:-1]) | (dp[1:] != dp[:-1])]))
        for first, end in zip(begin.tolist(), [*begin[1:].tolist(), len(sp)]):
            for lo in range(first, end, PACK):
                yield int(sp[first]), int(dp[first]), [c[lo : min(lo + PACK, end)] for c in cols]

    held: list[pa.RecordBatch] = []
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
        if sum(h.num_rows for h in held) >= GATHER:
            yield from cut_up(held)
            held = []
    if held:
        yield from cut_up(held)


def _marks(route) -> np.ndarray:
    mark = np.zeros(len(route), dtype=np.uint8)
    for name, code in MARKS.items():
        mark[pc.equal(route, name).fill_null(False).to_numpy()] = code
    return mark


def _ends(s: int, d: int, a: np.ndarray, b: np.ndarray, w: bytes, mark: np.ndarray) -> list[tuple]:
    """The records of a pair's edges, one for either end."""
    blobs = (a.tobytes(), b.tobytes(), w, mark.tobytes())
    return [(s, 1, None, *blobs)] if s == d else [(s, 2, d, *blobs), (d, 4, s, *blobs)]


def _weights(w: np.ndarray) -> bytes:
    return b"" if (w == 1).all() else w.astype(np.float64).tobytes()


def _in_batches(rows: Iterator[tuple], make, most: int = 256):
    held = []
    for row in rows:
        held.append(row)
        if len(held) >= most:
            yield make(held)
            held = []
    if held:
        yield make(held)


def _pack_edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (sp, dp, src, dst, w, route) to packed records of a pair of parts, one for either end."""
    packed = _by_pair(batches, ("src", "dst", "w", "route"))
    yield from _in_batches((r for s, d, (a, b, w, mark) in packed for r in _ends(s, d, a, b, _weights(w), mark)), _records)


def _pack_fixed(route: str):
    """Rows (sp, dp, src, dst, w) to the same records, all remote edges of one route."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed = _by_pair(batches, ("src", "dst", "w"))
        mark = lambda s, d, n: np.full(n, 0 if s == d else MARKS[route], dtype=np.uint8)
        yield from _in_batches((r for s, d, (a, b, w) in packed for r in _ends(s, d, a, b, _weights(w), mark(s, d, len(a)))), _records)

    return run


PAIRED = "sp int, dp int, n int, a binary, b binary, w binary"


def _pack_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (sp, dp, src, dst, w) to packed records of a pair of parts, not routed yet."""
    types = [pa.int32()] * 3 + [pa.binary()] * 3
    make = lambda rows: pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=["sp", "dp", "n", "a", "b", "w"])
    packed = _by_pair(batches, ("src", "dst", "w"))
    yield from _in_batches(((s, d, len(a), a.tobytes(), b.tobytes(), _weights(w)) for s, d, (a, b, w) in packed), make)


def _joined_edges(rows: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(a, b, w) of records whose blobs are sources, destinations and weights; w is None where all are one."""
    a, b = (np.frombuffer(b"".join(r[i] for r in rows), dtype=np.int64) for i in (0, 1))
    w = np.concatenate([np.frombuffer(r[2]) if r[2] else np.ones(len(r[0]) // 8) for r in rows]) if any(r[2] for r in rows) else None
    return a, b, w


def _route_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Packed pairs, sorted by (sp, dp), to records for either end under the minimum cover; local edges as they are."""

    def rows() -> Iterator[tuple]:
        for (s, d), t in groups(batches, 2):
            a, b, w = _joined_edges(list(zip(*(t[c].to_pylist() for c in ("a", "b", "w")))))
            if s == d:
                post = np.zeros(len(a), dtype=np.uint8)
            else:
                u, v = (np.unique(x, return_inverse=True)[1] for x in (a, b))
                post = konig_cover(u, v)[0][u].astype(np.uint8)  # the code of its route
            for lo in range(0, len(a), PACK):
                cut_ = slice(lo, lo + PACK)
                yield from _ends(s, d, a[cut_], b[cut_], b"" if w is None else w[cut_].tobytes(), post[cut_])

    yield from _in_batches(rows(), _records)


def _unpacked(part: int, records: Iterator[tuple[int, int, list[tuple]]]) -> dict:
    """A part's arrays from (kind, other, packed records), which rise: those of one other part at a time are in memory."""
    whole = lambda held, i, t: np.frombuffer(b"".join(r[i] for r in held), dtype=t)
    ahead = next(records, None)

    def of(kind: int) -> Iterator[tuple[int, list[tuple]]]:
        nonlocal ahead
        while ahead and ahead[0] == kind:
            _, other, held = ahead
            ahead = None
            yield other, held
            del held
            ahead = next(records, None)

    def pairs(kind: int) -> Iterator[tuple[int, tuple]]:
        for other, held in of(kind):
            (a, b, w), mark = _joined_edges(held), whole(held, 3, np.uint8)
            held.clear()
            yield other, (a, b, w, None if (mark == MARKS["edge"]).any() else mark == MARKS["post"])

    def alone(kind: int) -> list[tuple]:
        return [r for _, held in of(kind) for r in held]

    nodes = alone(0)
    ids = whole(nodes, 0, np.int64)
    x = whole(nodes, 1, np.float64).reshape(len(ids), -1) if len(ids) else np.zeros((0, 0))
    return _arranged(part, ids, x, whole(nodes, 2, np.int64), whole(nodes, 3, np.int64), _joined_edges(alone(1)), pairs(2), pairs(4))


def _build_parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Packed records, sorted by part, kind and other part, to the pieces of every part's arrays."""
    found = ((*key, list(zip(*(t[c].to_pylist() for c in ("a", "b", "w", "mark"))))) for key, t in groups(batches, 3))
    for part, mine in groupby(found, lambda r: r[0]):
        for seq, piece in enumerate(chunks(_unpacked(part, (r[1:] for r in mine)))):
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([piece], pa.binary())], names=["part", "seq", "payload"])


ROW = "part int, seq int, payload binary"


def chunks(value) -> list[bytes]:
    """Pieces of about ``CHUNK`` bytes: a pickle without its arrays, and the arrays' bytes behind it, which are read in place."""
    arrays: list[pickle.PickleBuffer] = []
    head = pickle.dumps(value, protocol=5, buffer_callback=arrays.append)
    pieces, places = [[]], []  # places: (piece, offset, bytes) of an array; one above ``CHUNK`` spans pieces of its own
    size = len(head)
    for a in arrays:
        raw = a.raw()
        n, pad = raw.nbytes, -raw.nbytes % 16  # arrays stay aligned
        if n > CHUNK:
            places.append((len(pieces), 0, n))
            pieces += [*([raw[i : i + CHUNK]] for i in range(0, n, CHUNK)), []]
            size = 0
            continue
        if size + n > CHUNK:
            pieces.append([])
            size = 0
        places.append((len(pieces) - 1, sum(len(x) for x in pieces[-1]), n))
        pieces[-1] += [raw, bytes(pad)]
        size += n + pad
    front = pickle.dumps((head, places))
    pieces[0] = [len(front).to_bytes(8, "little"), front, bytes(-(8 + len(front)) % 16), *pieces[0]]
    return [b"".join(p) for p in pieces]


def joined(pieces: dict[int, bytes]):
    """The value of :func:`chunks`; its arrays are read-only views of the pieces, which go where an array spans them."""
    n = 8 + int.from_bytes(pieces[0][:8], "little")
    head, places = pickle.loads(memoryview(pieces[0])[8:n])

    def array(piece: int, offset: int, size: int):
        if size <= CHUNK:
            begin = offset if piece else offset + n + -n % 16
            return memoryview(pieces[piece])[begin : begin + size]
        return b"".join([pieces.pop(piece + i) for i in range(-(-size // CHUNK))])

    return pickle.loads(head, buffers=[array(*p) for p in places])


def _routed(spark: SparkSession, located: DataFrame, route: str, max_pair_edges: int) -> DataFrame:
    """Packed records of all edges for both of their ends.

    Edges travel as packed arrays: a row per edge and end would be sorted and taken apart row by row.
    """
    if route in MARKS:  # no pair has to be seen whole
        return cut(spark, located.mapInArrow(_pack_fixed(route), PACKED), "packed", narrow=True)
    if route == "hybrid":
        pairs = cut(spark, located.mapInArrow(_pack_pairs, PAIRED), "pairs", narrow=True)
        large = pairs.filter("sp <> dp").groupBy("sp", "dp").agg(F.sum("n").alias("e")).agg(F.max("e")).first()[0] or 0
        if large <= max_pair_edges:
            return pairs.repartition("sp", "dp").sortWithinPartitions("sp", "dp").mapInArrow(_route_pairs, PACKED)
    located = cut(spark, located, "located")
    here, away = remote.split(located)
    options = {"max_pair_edges": max_pair_edges} if route == "hybrid" else {}
    routed = remote.plan(away, route, **options).select("sp", "dp", "src", "dst", "w", "route")
    both = routed.unionByName(here.select("sp", "dp", "src", "dst", "w", F.lit(None).cast("string").alias("route")))
    return cut(spark, both.mapInArrow(_pack_edges, PACKED), "packed", narrow=True)


def prepare(graph: Graph, parts: DataFrame | None, cfg: TrainConfig, n_parts: int, max_pair_edges: int = MAX_PAIR_EDGES) -> Prepared:
    """Route the remote edges once and gather every part into its row.

    ``parts`` None is the partition ``id mod n_parts`` of a graph whose edges join nodes only: no join locates them.
    """
    spark = graph.nodes.sparkSession
    ship(spark)
    edges = layers.with_gcn_weights(graph.edges) if cfg.model == "gcn" else graph.edges
    located = remote.located_by_mod(edges, n_parts) if parts is None else remote.located(edges, parts)
    packed = _routed(spark, located, cfg.route, max_pair_edges)
    if parts is None:
        placed = graph.nodes.filter("id is not null").withColumn("part", F.pmod("id", F.lit(n_parts)).cast("int"))
    else:
        placed = graph.nodes.join(parts, "id")
    nodes = placed.select("part", "id", "feat", "label", "split").mapInArrow(_pack_nodes, PACKED)
    # by number: coalesced by bytes, all parts of narrow edges would be built in one task
    both = packed.unionByName(nodes).withColumn("other", F.coalesce("other", F.lit(-1)))
    dealt = both.repartition(4 * n_parts, "part").sortWithinPartitions("part", "kind", "other")
    # packed records are large: a batch of them is bounded by its bytes
    table = cut(spark, dealt.mapInArrow(_build_parts, ROW), "parts", batch_bytes=16 << 20)
    sizes = graph.nodes.agg(F.max(F.size("feat")).alias("width"), F.max("label").alias("label"), F.count(F.lit(1)).alias("n")).first()
    return Prepared(table, n_parts, sizes.width, (sizes.label or 0) + 1, sizes.n)


# ---------------------------------------------------------------- parameters


def init_params(cfg: TrainConfig, width: int, classes: int) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(cfg.seed)
    sizes = [width] + [cfg.hidden] * (cfg.layers - 1) + [classes]
    p = {"embed": rng.normal(0, 0.1, (classes, width))}
    for k, (a, b) in enumerate(zip(sizes[:-1], sizes[1:])):
        bound = math.sqrt(6 / (a + b))
        p[f"self{k}"], p[f"nbr{k}"], p[f"bias{k}"] = rng.uniform(-bound, bound, (a, b)), rng.uniform(-bound, bound, (a, b)), np.zeros(b)
        p[f"gain{k}"], p[f"shift{k}"] = np.ones(a), np.zeros(a)
    return p


class Adam:
    def __init__(self, lr: float, b1: float = 0.9, b2: float = 0.999):
        self.lr, self.b1, self.b2, self.t, self.m, self.v = lr, b1, b2, 0, {}, {}

    def step(self, p: dict, g: dict) -> None:
        self.t += 1
        for k, x in g.items():
            self.m[k] = self.b1 * self.m.get(k, 0) + (1 - self.b1) * x
            self.v[k] = self.b2 * self.v.get(k, 0) + (1 - self.b2) * x * x
            p[k] = p[k] - self.lr * (self.m[k] / (1 - self.b1**self.t)) / (np.sqrt(self.v[k] / (1 - self.b2**self.t)) + 1e-8)


class Sgd:
    def __init__(self, lr: float):
        self.lr = lr

    def step(self, p: dict, g: dict) -> None:
        for k, x in g.items():
            p[k] = p[k] - self.lr * x


# ---------------------------------------------------------------- one superstep of one part


def segment_sum(n: int, seg: tuple, x: np.ndarray, chunk: int = 1 << 13) -> np.ndarray:
    """Weighted sums of rows of ``x`` over edges clustered by their target."""
    keys, starts, other, w = seg
    x = np.asarray(x, dtype=np.float64)
    out = np.zeros((n, x.shape[1]))
    ends = np.concatenate([starts[1:], [len(other)]]) if len(starts) else starts
    lo = 0
    while lo < len(keys):  # whole runs, about ``chunk`` edges at a time, which stay in the cache
        hi = max(lo + 1, int(np.searchsorted(ends, starts[lo] + chunk)))
        a, b = starts[lo], ends[hi - 1]
        rows = x.take(other[a:b], axis=0)
        if w is not None:
            rows *= w[a:b, None]
        out[keys[lo:hi]] = np.add.reduceat(rows, starts[lo:hi] - a, axis=0)
        lo = hi
    return out


def add_rows(out: np.ndarray, at: np.ndarray, x: np.ndarray) -> None:
    """Add rows to those of ``out`` at rising places; equal places add up."""
    first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]])) if len(at) else at
    if len(first):
        out[at[first]] += x if len(first) == len(at) else np.add.reduceat(x, first, axis=0)


class Worker:
    """What a part does in one epoch; :meth:`state` is what it keeps between supersteps."""

    def __init__(self, part: dict, p: dict, cfg: TrainConfig, epoch: int, mode: str, cache: dict | None):
        self.d, self.p, self.cfg, self.epoch, self.mode, self.cache = part, p, cfg, epoch, mode, cache
        self.saved: list[dict] = []
        self.grads: dict[str, np.ndarray] = {}
        self.new_cache: dict = {}
        self.vectors = self.bytes = self.param_bytes = 0
        self.stats: dict = {}

    def state(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("d", "p", "cfg", "cache")}

    def resume(self, state: dict) -> None:
        self.__dict__.update(state)

    @property
    def exchanging(self) -> bool:
        return self.mode == "eval" or self.cfg.stale_lag > 0 or self.epoch % self.cfg.refresh_every == 0 or self.cache is None

    @property
    def using_cache(self) -> bool:
        return self.mode != "eval" and self.cache is not None and (self.cfg.stale_lag > 0 or not self.exchanging)

    @property
    def caching(self) -> bool:
        return self.cfg.refresh_every > 1 or self.cfg.stale_lag > 0

    def rng(self, *key: int) -> np.random.Generator:
        return np.random.default_rng([self.cfg.seed, self.epoch, *key])

    # -- messages

    def _kept(self, layer: int, sp: int, dp: int, n: int) -> np.ndarray:
        if self.cfg.boundary_rate >= 1 or self.mode == "eval":
            return np.ones(n, dtype=bool)
        return self.rng(3, layer, sp, dp).random(n) < self.cfg.boundary_rate

    def pack(self, x: np.ndarray, layer: int, to: int, back: bool) -> bytes:
        me = self.d["part"]
        keep = self._kept(layer, to if back else me, me if back else to, len(x))
        if not keep.all():
            x = x[keep] / self.cfg.boundary_rate
        bits = 32
        if self.cfg.bits < 32 and (self.cfg.q_backward if back else self.cfg.q_forward) and x.size:
            bits = self.bits_for(x) if self.cfg.adaptive else self.cfg.bits
        rng = self.rng(5, layer, me, to, int(back)) if bits < 32 and self.cfg.rounding == "stochastic" else None
        blob, data, params = to_message(x, bits, rng, self.cfg.group_rows)
        self.vectors += len(x)
        self.bytes += data
        self.param_bytes += params
        return blob

    def bits_for(self, x: np.ndarray) -> int:
        """The least bits whose codes are at most ``adaptive_error`` mean absolute values apart."""
        spread = float((x.max(axis=1) - x.min(axis=1)).mean() / (np.abs(x).mean() + 1e-12))
        return next((b for b in (2, 4) if spread <= self.cfg.adaptive_error * ((1 << b) - 1)), 8)

    def unpack(self, blob: bytes, n: int, layer: int, sender: int, back: bool) -> np.ndarray:
        me = self.d["part"]
        got = from_message(blob, self.cfg.group_rows)
        keep = self._kept(layer, me if back else sender, sender if back else me, n)
        if keep.all():
            return got
        out = np.zeros((n, got.shape[1]))
        out[keep] = got
        return out

    def send(self, layer: int, h: np.ndarray) -> dict[int, bytes]:
        if not self.exchanging:
            return {}
        return {dp: self.pack(np.vstack([h[r["post"]], segment_sum(r["n_pre"], r["pre"], h)]), layer, dp, False) for dp, r in self.d["send"].items()}

    def send_back(self, layer: int, d: np.ndarray) -> dict[int, bytes]:
        if not self.exchanging:
            return {}
        return {sp: self.pack(np.vstack([segment_sum(r["n_post"], r["post_t"], d), d[r["pre"]]]), layer, sp, True) for sp, r in self.d["recv"].items()}

    # -- forward

    def begin(self) -> dict[int, bytes]:
        x = self.d["x"]
        labelled = (self.d["split"] == 0) & (self.d["y"] >= 0)
        self.show = np.zeros(len(x), dtype=bool)
        if self.cfg.lp:
            self.show = labelled & (shown_rows(self.d["ids"], self.cfg.lp_rate, self.epoch, self.cfg.seed) if self.mode == "train" else True)
            x = x.copy()
            x[self.show] += self.p["embed"][self.d["y"][self.show]]
        self.loss_rows = labelled & ~self.show
        return self.enter(0, x)

    def enter(self, layer: int, h: np.ndarray) -> dict[int, bytes]:
        s: dict = {}
        if self.cfg.layer_norm:
            s["hn"], s["norm"] = layers.norm_rows(h, self.p[f"gain{layer}"], self.p[f"shift{layer}"]) if len(h) else (h, (h, h))
        else:
            s["hn"] = h
        self.saved.append(s)
        return self.send(layer, s["hn"])

    def finish_layer(self, layer: int, inbox: dict[int, bytes]) -> np.ndarray:
        s, n = self.saved[layer], len(self.d["ids"])
        far = np.zeros_like(s["hn"])
        for sp in sorted(inbox):
            r = self.d["recv"][sp]
            got = self.unpack(inbox[sp], r["n_post"] + len(r["pre"]), layer, sp, False)
            far += segment_sum(n, r["post"], got[: r["n_post"]])
            add_rows(far, r["pre"], got[r["n_post"] :])
        if self.exchanging and self.caching:
            self.new_cache[layer] = far
        if self.using_cache:
            far = self.cache[layer]
        agg = segment_sum(n, self.d["here"], s["hn"]) + far
        p = self.p
        if self.cfg.model == "sage":
            agg /= np.maximum(self.d["deg"], 1)[:, None]
            z = s["hn"] @ p[f"self{layer}"] + agg @ p[f"nbr{layer}"] + p[f"bias{layer}"]
        elif self.cfg.model == "gcn":
            z = agg @ p[f"nbr{layer}"] + p[f"bias{layer}"]
        else:  # gin: own vector and neighbours' sum share the weights
            z = (s["hn"] + agg) @ p[f"nbr{layer}"] + p[f"bias{layer}"]
        s["agg"] = agg
        if self.mode == "eval":
            s.clear()
        return z

    def activate(self, layer: int, z: np.ndarray) -> np.ndarray:
        s = self.saved[layer]
        s["live"] = z > 0
        if self.mode == "train" and self.cfg.dropout > 0:
            s["live"] &= self.rng(7, layer, self.d["part"]).random(z.shape) >= self.cfg.dropout
        return z * self.scale(layer)

    def scale(self, layer: int) -> np.ndarray:
        """What activation and dropout multiply a layer's outputs with."""
        return self.saved[layer]["live"] * (1 / (1 - self.cfg.dropout) if self.mode == "train" and self.cfg.dropout > 0 else 1.0)

    # -- backward

    def layer_back(self, layer: int, dz: np.ndarray) -> dict[int, bytes]:
        s, p, g = self.saved[layer], self.p, self.grads
        g[f"bias{layer}"] = dz.sum(axis=0)
        if self.cfg.model == "sage":
            g[f"self{layer}"], g[f"nbr{layer}"] = s["hn"].T @ dz, s["agg"].T @ dz
            s["d"], dagg = dz @ p[f"self{layer}"].T, dz @ p[f"nbr{layer}"].T / np.maximum(self.d["deg"], 1)[:, None]
        elif self.cfg.model == "gcn":
            g[f"nbr{layer}"] = s["agg"].T @ dz
            s["d"], dagg = np.zeros_like(s["hn"]), dz @ p[f"nbr{layer}"].T
        else:
            g[f"nbr{layer}"] = (s["hn"] + s["agg"]).T @ dz
            s["d"] = dagg = dz @ p[f"nbr{layer}"].T
        s["d"] = s["d"] + segment_sum(len(dagg), self.d["here_t"], dagg)
        del s["hn"], s["agg"]  # the state holds what is still read
        return self.send_back(layer, dagg)

    def absorb_back(self, layer: int, inbox: dict[int, bytes]) -> np.ndarray:
        s = self.saved[layer]
        far = np.zeros_like(s["d"])
        for dp in sorted(inbox):
            r = self.d["send"][dp]
            got = self.unpack(inbox[dp], len(r["post"]) + r["n_pre"], layer, dp, True)
            add_rows(far, r["post"], got[: len(r["post"])])
            far += segment_sum(len(far), r["pre_t"], got[len(r["post"]) :])
        if self.cfg.stale_lag > 0:  # gradients arrive an epoch late too; delayed sums are constants between exchanges
            self.new_cache["back", layer] = far
            if self.using_cache:
                far = self.cache["back", layer]
        d = s["d"] + far
        if self.cfg.layer_norm and len(d):
            d, self.grads[f"gain{layer}"], self.grads[f"shift{layer}"] = layers.norm_rows_back(d, self.p[f"gain{layer}"], s["norm"])
        s.clear()
        return d

    # -- the superstep

    def step(self, t: int, inbox: dict[int, bytes]) -> tuple[dict[int, bytes], bool]:
        """(messages to send, is this the epoch's last superstep)."""
        n_layers = self.cfg.layers
        if t == 0:
            return self.begin(), False
        if t < n_layers:
            return self.enter(t, self.activate(t - 1, self.finish_layer(t - 1, inbox))), False
        if t == n_layers:
            logits = self.finish_layer(t - 1, inbox)
            self.score(logits)
            if self.mode == "eval":
                self.pred = logits.argmax(axis=1) if len(logits) else np.zeros(0, dtype=np.int64)
                return {}, True
            loss, dz = layers.softmax_loss(logits, self.d["y"], self.loss_rows)
            self.stats["loss"], self.stats["loss_rows"] = loss, int(self.loss_rows.sum())
            return self.layer_back(n_layers - 1, dz), False
        layer = 2 * n_layers - t
        d = self.absorb_back(layer, inbox)
        if layer:
            return self.layer_back(layer - 1, d * self.scale(layer - 1)), False
        embed = np.zeros_like(self.p["embed"])
        np.add.at(embed, self.d["y"][self.show], d[self.show])
        self.grads["embed"] = embed
        return {}, True

    def score(self, logits: np.ndarray) -> None:
        ok = (logits.argmax(axis=1) == self.d["y"]) & (self.d["y"] >= 0) if len(logits) else np.zeros(0, dtype=bool)
        for k, name in enumerate(SPLITS):
            rows = (self.d["split"] == k) & (self.d["y"] >= 0)
            self.stats[name] = (int(ok[rows].sum()), int(rows.sum()))


def _superstep(t: int, shared, cfgs: list[TrainConfig], epoch: int, mode: str):
    """Records (part, (kind, number, bytes)) of whole parts to those of the next superstep.

    Kinds: part, state, cache (in chunks), message (its number is the sender and the model), result,
    pred.  A task's input holds the last superstep's output beside what was exchanged; messages in it
    that are on their way to other tasks are passed over.
    """

    def run(task: int, records):
        held: dict[int, dict] = {}
        for part, (kind, number, blob) in records:
            if part == task:
                held.setdefault(part, {}).setdefault(kind, {})[number] = blob
        for part, mine in held.items():
            static = joined(mine["part"])
            cache = joined(mine["cache"]) if "cache" in mine and mode == "train" else {}
            state = joined(mine["state"]) if "state" in mine else {}
            inbox: list[dict[int, bytes]] = [{} for _ in cfgs]
            for (sender, m), blob in mine.get("message", {}).items():
                inbox[m][sender] = blob
            emit = lambda kind, value: ((part, (kind, i, c)) for i, c in enumerate(chunks(value)))  # noqa: E731, B023
            kept, done, sums, pred, last = {}, [], {}, [], False
            for m, cfg in enumerate(cfgs):
                worker = Worker(static, shared.value[m], cfg, epoch, mode, cache.get(m))
                if m in state:
                    worker.resume(state[m])
                out, last = worker.step(t, inbox[m])
                for to, blob in out.items():
                    yield to, ("message", (part, m), blob)
                if not last:
                    kept[m] = worker.state()
                    continue
                done.append({"grads": worker.grads, "stats": worker.stats, "vectors": worker.vectors, "bytes": worker.bytes, "param_bytes": worker.param_bytes})
                if cfg.refresh_every > 1 or cfg.stale_lag:
                    sums[m] = worker.new_cache if worker.new_cache else cache.get(m)
                if mode == "eval":
                    pred.append(worker.pred)
            if not last:
                yield from emit("state", kept)
                continue
            yield part, ("result", 0, pickle.dumps(done))
            if any(v is not None for v in sums.values()):
                yield from emit("cache", sums)
            if mode == "eval":
                yield part, ("pred", 0, pickle.dumps((static["ids"], pred)))

    return run


COUNTS = ("vectors", "bytes", "param_bytes")


def _total(rows: list[dict]) -> dict:
    out: dict = {"grads": {}, "stats": {}} | dict.fromkeys(COUNTS, 0)
    for r in rows:
        for k, g in r["grads"].items():
            out["grads"][k] = out["grads"].get(k, 0) + g
        for k, s in r["stats"].items():
            out["stats"][k] = tuple(a + b for a, b in zip(out["stats"].get(k, (0, 0)), s)) if isinstance(s, tuple) else out["stats"].get(k, 0) + s
        for k in COUNTS:
            out[k] += r[k]
    return out


def _of(kind: str, stays: bool):
    """The records of a kind; ``stays`` when they are in their part's task already."""
    return lambda records: records.mapPartitions(lambda it: (r for r in it if r[1][0] == kind), preservesPartitioning=stays)


class Epoch:
    """The supersteps of one epoch, a job each, over records; a context that releases what it persisted and sent.

    Several models may share the passes: they differ in parameters, seed, bits or label propagation,
    not in the graph, its routes or the number of layers.
    """

    def __init__(self, prep: Prepared, params: list[dict], cfgs: list[TrainConfig], epoch: int, mode: str = "train", cache: RDD | None = None):
        sc = prep.table.sparkSession.sparkContext
        self.parts, self.kept, self.moved = prep.parts, [], []
        self.shared = sc.broadcast(params)  # the models' parameters: their size does not grow with the graph
        fixed = prep.dealt() if cache is None else prep.dealt().union(cache)
        now = fixed
        for t in range((cfgs[0].layers if mode == "eval" else 2 * cfgs[0].layers) + 1):
            self.out = now.mapPartitionsWithIndex(_superstep(t, self.shared, cfgs, epoch, mode), preservesPartitioning=True).persist(KEPT)
            self.kept.append(self.out)
            self.out._jrdd.count()  # a count of the stored bytes: no pass through Python
            while len(self.kept) > 1:  # read for the last time by the superstep that has just ended
                self.kept.pop(0).unpersist()
            # the only exchange: messages go to their receiver's task
            self.moved.append(_sent(_of("message", False)(self.out), self.parts))
            now = fixed.union(self.out).union(self.moved[-1])

    def __enter__(self) -> Epoch:
        return self

    def __exit__(self, *_) -> None:
        for r in self.kept:
            r.unpersist()
        self.shared.unpersist()
        cleaner = self.out.ctx._jsc.sc().cleaner()
        if cleaner.isDefined():  # nothing reads an epoch's messages again; else their files stay until the driver's heap is collected
            for r in self.moved[:-1]:  # the last one is not run
                cleaner.get().doCleanupShuffle(_shuffle_of(r), True)

    def totals(self) -> list[dict]:
        """Per model: gradients, losses and counts."""
        results = _of("result", True)(self.out).map(lambda r: pickle.loads(r[1][2]))
        add = lambda a, b: [_total([x, y]) for x, y in zip(a, b)]
        if self.parts > COMBINE_OVER:  # gradients add up in a tree; the driver gets one record
            return results.treeReduce(add)
        return [_total(list(rows)) for rows in zip(*results.collect())]

    def cache(self) -> RDD:
        """Remote sums for later epochs, cut from this epoch's lineage."""
        checkpoint_root(self.out.ctx)
        rows = _of("cache", True)(self.out).persist(KEPT)
        rows.checkpoint()
        rows.count()
        return rows


def epoch_total(prep: Prepared, params: dict, cfg: TrainConfig, epoch: int, mode: str = "train") -> dict:
    """Gradients, losses and counts of one epoch without an update."""
    with Epoch(prep, [params], [cfg], epoch, mode) as e:
        return e.totals()[0]


def _forget(spark: SparkSession, cache: RDD | None) -> None:
    if cache is not None:
        cache.unpersist()
        drop(spark, cache.getCheckpointFile())


def sharing(prep: Prepared, cfgs: list[TrainConfig]) -> list[list[int]]:
    """Numbers of the models by pass: as many share one as have states of ``SHARED_STATE`` in a part, one at least."""
    # a layer keeps its input, normalized and not, its sums and its gradient
    state = max(4 * 8 * (prep.width + (c.layers - 1) * c.hidden) for c in cfgs) * -(-prep.nodes // prep.parts)
    n = max(1, SHARED_STATE // max(1, state))
    n = -(-len(cfgs) // -(-len(cfgs) // n))  # passes of about equal size
    return [list(range(i, min(i + n, len(cfgs)))) for i in range(0, len(cfgs), n)]


def fit_many(prep: Prepared, cfgs: list[TrainConfig], eval_every: int = 0, patience: int = 0) -> list[Result]:
    """Train several models of one graph in the same passes (a sweep of seeds or settings), or in few where they are large.

    History has loss, bytes and seconds per epoch, and accuracies every ``eval_every`` epochs.
    Counted bytes are those of vectors and parameters; ``shuffle_bytes`` are what Spark wrote for
    the exchanges of all models together.  With ``patience``, training stops once no model's best
    validation accuracy is younger than that many evaluations; each gets the parameters of its best.
    """
    if len({(c.layers, c.route, c.epochs, c.model == "gcn") for c in cfgs}) > 1:
        raise ValueError("models that share passes have one graph, one number of layers and one of epochs")
    params = [init_params(c, prep.width, prep.classes) for c in cfgs]
    opts = [Adam(c.lr) if c.optimizer == "adam" else Sgd(c.lr) for c in cfgs]
    spark, out = prep.table.sparkSession, [Result(p) for p in params]
    caching = any(c.refresh_every > 1 or c.stale_lag > 0 for c in cfgs)
    passes = sharing(prep, cfgs)
    caches: list[RDD | None] = [None] * len(passes)
    prep.dealt().count()  # the parts are dealt once, before the first epoch
    best, since = [-1.0] * len(cfgs), 0
    for epoch in range(cfgs[0].epochs):
        began, totals = time.time(), []
        with traffic(spark) as wire:
            for i, models in enumerate(passes):
                some = [cfgs[m] for m in models]
                with Epoch(prep, [params[m] for m in models], some, epoch, "train", caches[i]) as e:
                    totals += e.totals()
                    if caching and any(epoch % c.refresh_every == 0 or c.stale_lag for c in cfgs):
                        before, caches[i] = caches[i], e.cache()
                        _forget(spark, before)
        took, last = time.time() - began, epoch == cfgs[0].epochs - 1
        for m, total in enumerate(totals):
            n = max(1, total["stats"]["loss_rows"])
            params[m] = dict(params[m])
            opts[m].step(params[m], {k: g / n for k, g in total["grads"].items()})
            out[m].sent_bytes += total["bytes"]
            out[m].param_bytes += total["param_bytes"]
            out[m].shuffle_bytes += wire.bytes
            out[m].history.append({"epoch": epoch, "loss": total["stats"]["loss"] / n, "seconds": took, "shuffle_bytes": wire.bytes} | {k: total[k] for k in COUNTS})
        if eval_every and ((epoch + 1) % eval_every == 0 or last):
            since += 1
            for m, acc in enumerate(evaluate_many(prep, params, cfgs)):
                out[m].history[-1] |= acc
                if acc["val_accuracy"] > best[m]:
                    best[m], since, out[m].params = acc["val_accuracy"], 0, params[m]
            if patience and since >= patience:
                break
    if not (eval_every and patience):
        for m, r in enumerate(out):
            r.params = params[m]
    for cache in caches:
        _forget(spark, cache)
    return out


def fit(prep: Prepared, cfg: TrainConfig, eval_every: int = 0, patience: int = 0) -> Result:
    """Train one model; see :func:`fit_many`."""
    return fit_many(prep, [cfg], eval_every, patience)[0]


def evaluate_many(prep: Prepared, params: list[dict], cfgs: list[TrainConfig]) -> list[dict[str, float]]:
    """Accuracy per split: no dropout, every training label shown, none of the others."""
    totals = []
    for models in sharing(prep, cfgs):
        with Epoch(prep, [params[m] for m in models], [cfgs[m] for m in models], 0, "eval") as e:
            totals += e.totals()
    return [{f"{k}_accuracy": t["stats"][k][0] / max(1, t["stats"][k][1]) for k in SPLITS} for t in totals]


def evaluate(prep: Prepared, params: dict, cfg: TrainConfig) -> dict[str, float]:
    return evaluate_many(prep, [params], [cfg])[0]


def predict(prep: Prepared, params: dict, cfg: TrainConfig) -> DataFrame:
    """(id, pred) of every node."""
    spark = prep.table.sparkSession

    def rows(record):
        ids, (pred,) = pickle.loads(record[1][2])
        return zip(ids.tolist(), pred.tolist())

    with Epoch(prep, [params], [cfg], 0, "eval") as e:
        return cut(spark, spark.createDataFrame(_of("pred", True)(e.out).flatMap(rows), "id long, pred int"), "predictions")


def history_frame(spark: SparkSession, result: Result) -> DataFrame:
    rows = [(int(r["epoch"]), float(r["loss"]), float(r.get("test_accuracy", float("nan"))), int(r["bytes"]), int(r["param_bytes"]), int(r["shuffle_bytes"])) for r in result.history]
    return spark.createDataFrame(rows, "epoch int, loss double, test_accuracy double, sent_bytes long, param_bytes long, shuffle_bytes long")


def ablation(prep: Prepared, cfg: TrainConfig, seeds: tuple[int, ...] = (0,), eval_every: int = 0, patience: int = 0) -> list[dict]:
    """Full precision and 2 bits, with and without label propagation, all in the same passes.

    With ``patience`` the accuracies are those of each model's best evaluation on the validation split.
    """
    cfgs = [replace(cfg, bits=bits, lp=lp, seed=seed) for bits in (32, 2) for lp in (False, True) for seed in seeds]
    done = fit_many(prep, cfgs, eval_every, patience)
    final = evaluate_many(prep, [r.params for r in done], cfgs)
    return [{"bits": c.bits, "lp": c.lp, "seed": c.seed, "sent_bytes": r.sent_bytes, "param_bytes": r.param_bytes, "epochs": len(r.history), "history": r.history} | acc for c, r, acc in zip(cfgs, done, final)]
