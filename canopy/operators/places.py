"""Where parameters and nodes go when leaves are absorbed or come out again, for whole batches of letters.

A letter of a wide tree has as many parameters as its node has children, so these are sorts and sums over all
cells of a batch; an expression that looks up a parameter for each leaf takes time of their product and more.
"""

from __future__ import annotations

from functools import lru_cache
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

PARAMS = "array<struct<id:int,off:bigint,up:bigint,at:int>>"
ITEMS = "array<struct<pre:bigint,parent:bigint,slot:int,sym:bigint,inside:array<bigint>>>"


@lru_cache(maxsize=None)
def udfs() -> SimpleNamespace:
    """The functions; nested, so that they travel by value and an executor needs no package."""

    def numbers(x: pa.Array) -> np.ndarray:
        return pc.fill_null(x, 0).to_numpy(zero_copy_only=False).astype(np.int64)

    def cells(lists: pa.Array, *names: str):
        """Row of each cell, and its fields; rows that are null have none."""
        row = np.repeat(np.arange(len(lists)), numbers(pc.list_value_length(lists)))
        flat = lists.flatten()
        if not names:
            return row, numbers(flat)
        fields = dict(zip([f.name for f in flat.type], flat.flatten()))
        return row, *(numbers(fields[n]) for n in names)

    def found(row: np.ndarray, key: np.ndarray, x_row: np.ndarray, x_key: np.ndarray) -> np.ndarray:
        """Index of the cell of the same row and key."""
        all_, want = (row << 32) + key, (x_row << 32) + x_key
        order = np.argsort(all_, kind="stable")
        at = np.minimum(np.searchsorted(all_[order], want), max(len(order) - 1, 0))
        if len(want) and (not len(order) or (all_[order[at]] != want).any()):
            raise ValueError("a leaf at no parameter")
        return order[at] if len(want) else np.zeros(0, np.int64)

    def sums(row: np.ndarray, key: np.ndarray, x_row: np.ndarray, x_key: np.ndarray, x_n: np.ndarray, side: str) -> np.ndarray:
        """For each cell the total of the x of its row whose key is less ("left"), or no greater ("right")."""
        rank = np.unique(np.concatenate((key, x_key)), return_inverse=True)[1].reshape(-1)
        span = len(rank) + 1
        at, x = row * span + rank[: len(key)], x_row * span + rank[len(key) :]
        order = np.argsort(x, kind="stable")
        x, total = x[order], np.concatenate(([0], np.cumsum(x_n[order])))
        return total[np.searchsorted(x, at, side)] - total[np.searchsorted(x, row * span)]

    def lists(row: np.ndarray, n: int, values: pa.Array) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(np.bincount(row, minlength=n)))).astype(np.int32)), values)

    def struct(**fields) -> pa.Array:
        return pa.StructArray.from_arrays(list(fields.values()), list(fields))

    def moved(params, leaves, ordered: bool):
        row, id_, off, up, at = cells(params, "id", "off", "up", "at")
        x_row, slot, w = cells(leaves, "slot", "w")
        h = found(row, id_, x_row, slot)
        rest = np.ones(len(row), bool)
        rest[h] = False
        new_off, new_up = off + sums(row, id_, x_row, slot, w, "left"), up + sums(row, up, x_row, off[h], w, "right")
        gone = 0 if ordered else np.bincount(x_row, minlength=len(params))[row]
        keep = lambda x, kind: pa.array(x[rest], kind)
        return lists(row[rest], len(params), struct(id=keep(id_ - gone, pa.int32()), off=keep(new_off, pa.int64()), up=keep(new_up, pa.int64()), at=keep(at, pa.int32())))

    @F.arrow_udf(PARAMS)
    def in_order(params: pa.Array, leaves: pa.Array) -> pa.Array:
        return moved(params, leaves, True)

    @F.arrow_udf(PARAMS)
    def unordered(params: pa.Array, leaves: pa.Array) -> pa.Array:
        return moved(params, leaves, False)

    @F.arrow_udf(ITEMS)
    def opened(pre: pa.Array, parent: pa.Array, slot: pa.Array, rhs: pa.Array, own: pa.Array, weights: pa.Array, inside: pa.Array) -> pa.Array:
        n = len(rhs)
        all_row, sym, place = cells(rhs, "sym", "at")
        head = np.append(True, all_row[1:] != all_row[:-1])[: len(all_row)]
        row, id_, off, up, at = cells(own, "id", "off", "up", "at")
        x_row, x_at, x_w = all_row[~head], place[~head], cells(weights)[1][~head]
        h = found(row, id_, x_row, x_at)
        given = np.ones(len(row), bool)
        given[h] = False
        size = np.empty(len(row), np.int64)  # of what hangs at each parameter of the first part: an absorbed leaf, or the next that was given
        size[h], size[given] = x_w, cells(inside)[1]
        base = numbers(pre)
        out_pre, out_parent, out_slot = (np.empty(len(all_row), np.int64) for _ in range(3))
        none = np.zeros(len(all_row), bool)
        top = all_row[head]
        out_pre[head], out_parent[head], out_slot[head] = base[top], numbers(parent)[top], numbers(slot)[top]
        none[head] = parent.is_null().to_numpy(zero_copy_only=False)[top]
        out_pre[~head] = base[x_row] + off[h] + sums(x_row, x_at, row, id_, size, "left")
        out_parent[~head] = base[x_row] + up[h] + sums(x_row, up[h], row, off, size, "right")
        out_slot[~head] = at[h]
        many = np.zeros(len(all_row), np.int64)
        many[head] = np.bincount(row, minlength=n)[top]
        held = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(many))).astype(np.int32)), pa.array(size))
        return lists(all_row, n, struct(pre=pa.array(out_pre), parent=pa.array(out_parent, mask=none), slot=pa.array(out_slot.astype(np.int32), mask=none), sym=pa.array(sym), inside=held))

    @F.arrow_udf("struct<high:bigint,deep:array<struct<id:int,depth:bigint>>>")
    def depths(high: pa.Array, deep: pa.Array, leaves: pa.Array) -> pa.Array:
        row, id_, depth = cells(deep, "id", "depth")
        x_row, at, x_high = cells(leaves, "at", "high")
        h = found(row, id_, x_row, at)
        most = numbers(high)
        np.maximum.at(most, x_row, depth[h] + x_high)
        rest = np.ones(len(row), bool)
        rest[h] = False
        return struct(high=pa.array(most), deep=lists(row[rest], len(high), struct(id=pa.array(id_[rest], pa.int32()), depth=pa.array(depth[rest]))))

    return SimpleNamespace(in_order=in_order, unordered=unordered, opened=opened, depths=depths)
