"""Restriction, extension, local matrices, and one packed row a part."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.operators.overlap import routes
from overlapsolve.session import checkpoint
from overlapsolve.system import Sys


def restrict(vec: DataFrame, member: DataFrame) -> DataFrame:
    """(p, slot, i, x): the vector's values on each set."""
    return member.join(vec, "i").select("p", "slot", "i", "x")


def extend(local: DataFrame) -> DataFrame:
    """(i, x): local values (p, i, x) added up."""
    return local.groupBy("i").agg(F.sum("x").alias("x"))


def local_matrices(entries: DataFrame, member: DataFrame) -> DataFrame:
    """(p, r, c, a): principal submatrices by slots."""
    rows = member.select("p", "i", F.col("slot").alias("r"))
    cols = member.select("p", F.col("i").alias("j"), F.col("slot").alias("c"))
    return entries.join(rows, "i").join(cols, ["p", "j"]).select("p", "r", "c", "a")


def residual_global(entries: DataFrame, u: DataFrame, f: DataFrame) -> DataFrame:
    """(i, x): f - A u."""
    au = entries.join(u.withColumnRenamed("i", "j"), "j").groupBy("i").agg(F.sum(F.col("a") * F.col("x")).alias("y"))
    return f.join(au, "i", "left").select("i", (F.col("x") - F.coalesce("y", F.lit(0.0))).alias("x"))


def local_residual(entries: DataFrame, member: DataFrame, w: DataFrame, f: DataFrame) -> DataFrame:
    """(p, i, s): each part's own share of the residual from iterates w (p, i, x): masked load minus local matrix times masked iterate."""
    owned = member.where("owned").select("p", "i")
    load = owned.join(f, "i").select("p", "i", F.col("x").alias("s"))
    masked = owned.join(w, ["p", "i"]).select("p", F.col("i").alias("j"), "x")
    flow = masked.join(entries, "j").select("p", "i", (-F.col("a") * F.col("x")).alias("s"))
    return load.union(flow).groupBy("p", "i").agg(F.sum("s").alias("s"))


def accumulate(slabs: DataFrame, member: DataFrame) -> DataFrame:
    """(p, i, r): shares added up over all parts that have a value on a set's nodes."""
    return member.select("p", "i").join(slabs.groupBy("i").agg(F.sum("s").alias("r")), "i", "left").select("p", "i", F.coalesce("r", F.lit(0.0)).alias("r"))


def residual_norm(r: DataFrame, member: DataFrame) -> DataFrame:
    """(norm): from local parts (p, i, r), each node counted where it is owned."""
    own = member.where("owned").select("p", "i")
    return r.join(own, ["p", "i"]).agg(F.sqrt(F.sum(F.col("r") * F.col("r"))).alias("norm"))


def assemble_solution(w: DataFrame, member: DataFrame) -> DataFrame:
    """(i, x): owned values of the iterates (p, i, x)."""
    return w.join(member.where("owned").select("p", "i"), ["p", "i"]).select("i", "x")


@dataclass
class Block:
    """One part: its matrix in row form, load, mask, what it shares with whom, and its coarse weights."""

    p: int
    ids: np.ndarray
    owned: np.ndarray
    indptr: np.ndarray
    indices: np.ndarray
    data: np.ndarray
    rhs: np.ndarray
    peers: np.ndarray  # other parts, ascending
    peer_ptr: np.ndarray
    peer_slots: np.ndarray  # own slots shared with each peer, by node id: both sides list the same nodes in the same order
    coarse_slot: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    coarse_id: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    coarse_w: np.ndarray = field(default_factory=lambda: np.zeros(0))

    @property
    def n(self) -> int:
        return len(self.ids)

    def times(self, x: np.ndarray) -> np.ndarray:
        rows = np.repeat(np.arange(self.n), np.diff(self.indptr))
        return np.bincount(rows, weights=self.data * x[self.indices], minlength=self.n)

    def slab(self, w: np.ndarray) -> np.ndarray:
        """The part's share of the residual on its whole set."""
        return np.where(self.owned, self.rhs, 0.0) - self.times(np.where(self.owned, w, 0.0))

    def shared(self, k: int) -> np.ndarray:
        return self.peer_slots[self.peer_ptr[k] : self.peer_ptr[k + 1]]

    def outgoing(self, s: np.ndarray) -> list[tuple[int, np.ndarray]]:
        return [(int(q), s[self.shared(k)]) for k, q in enumerate(self.peers)]

    def accumulated(self, s: np.ndarray, incoming: dict[int, np.ndarray]) -> np.ndarray:
        """Own share plus the peers'; they are added in order of their numbers."""
        r = s.copy()
        for k, q in enumerate(self.peers):
            if int(q) in incoming:
                r[self.shared(k)] += incoming[int(q)]
        return r

    def to_coarse(self, s: np.ndarray, n0: int) -> np.ndarray:
        """The whole share projected: it is a partial residual, so rows that aren't owned count too."""
        return np.bincount(self.coarse_id, weights=self.coarse_w * s[self.coarse_slot], minlength=n0)

    def from_coarse(self, v0: np.ndarray) -> np.ndarray:
        return np.bincount(self.coarse_slot, weights=self.coarse_w * v0[self.coarse_id], minlength=self.n)

    @staticmethod
    def of(row: dict) -> Block:
        a = {k: np.asarray(row[k]) for k in row if k != "p"}
        return Block(row["p"], a["ids"].astype(np.int64), a["owned"].astype(bool), a["indptr"].astype(np.int64), a["indices"].astype(np.int64), a["data"].astype(float), a["rhs"].astype(float), a["peers"].astype(np.int64), a["peer_ptr"].astype(np.int64), a["peer_slots"].astype(np.int64), a["coarse_slot"].astype(np.int64), a["coarse_id"].astype(np.int64), a["coarse_w"].astype(float))


BLOCK_SCHEMA = (
    "p int, ids array<bigint>, owned array<boolean>, indptr array<int>, indices array<int>, data array<double>, rhs array<double>, "
    "peers array<int>, peer_ptr array<int>, peer_slots array<int>, coarse_slot array<int>, coarse_id array<int>, coarse_w array<double>"
)


def pack_blocks(sys: Sys) -> DataFrame:
    """One row a part, as in BLOCK_SCHEMA. A part is bounded by its partition, and so is the group that packs it."""
    m = sys.member
    tagged = [
        m.join(sys.rhs, "i", "left").select("p", F.lit(0).alias("tag"), F.col("slot").cast("long").alias("r"), F.col("i").alias("c"), F.coalesce("x", F.lit(0.0)).alias("a"), F.col("owned").cast("int").alias("q")),
        local_matrices(sys.entries, m).select("p", F.lit(1), F.col("r").cast("long"), F.col("c").cast("long"), "a", F.lit(0)),
        routes(m).select(F.col("src").alias("p"), F.lit(2), F.col("src_slot").cast("long"), F.col("i"), F.lit(0.0), F.col("dst").alias("q")),
    ]
    if sys.interp is not None:
        tagged.append(m.join(sys.interp, "i").select("p", F.lit(3), F.col("slot").cast("long"), F.col("c").cast("long"), F.col("weight"), F.lit(0)))
    rows = tagged[0]
    for t in tagged[1:]:
        rows = rows.union(t)

    def pack(key: tuple, table: pa.Table) -> pa.Table:
        tag, r, c, a, q = (table.column(n).to_numpy() for n in ("tag", "r", "c", "a", "q"))

        def part(k: int, *order: str) -> list[np.ndarray]:
            cols = {"r": r, "c": c, "q": q}
            at = np.flatnonzero(tag == k)
            at = at[np.lexsort(tuple(cols[o][at] for o in reversed(order)))]
            return [r[at], c[at], a[at], q[at]]

        slots, ids, rhs, owned = part(0, "r")
        rows_, cols_, data, _ = part(1, "r", "c")
        sslot, _, _, dst = part(2, "q", "c")
        cslot, cid, cw, _ = part(3, "r", "c")
        peers, first = np.unique(dst, return_index=True)
        out = {
            "p": [key[0].as_py()], "ids": [ids], "owned": [owned.astype(bool)], "indptr": [np.searchsorted(rows_, np.arange(len(slots) + 1)).astype(np.int32)],
            "indices": [cols_.astype(np.int32)], "data": [data], "rhs": [rhs], "peers": [peers.astype(np.int32)], "peer_ptr": [np.append(first, len(dst)).astype(np.int32)],
            "peer_slots": [sslot.astype(np.int32)], "coarse_slot": [cslot.astype(np.int32)], "coarse_id": [cid.astype(np.int32)], "coarse_w": [cw],
        }
        kinds = {"p": pa.int32(), "ids": pa.list_(pa.int64()), "owned": pa.list_(pa.bool_()), **{k: pa.list_(pa.int32()) for k in ("indptr", "indices", "peers", "peer_ptr", "peer_slots", "coarse_slot", "coarse_id")}, **{k: pa.list_(pa.float64()) for k in ("data", "rhs", "coarse_w")}}
        return pa.table({k: pa.array([v[0].tolist() if k != "p" else v[0]], kinds[k]) for k, v in out.items()})

    return checkpoint(rows.groupBy("p").applyInArrow(pack, BLOCK_SCHEMA))
