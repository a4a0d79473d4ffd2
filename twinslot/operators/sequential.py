"""One insertion at a time: the reference for batch placement, with the length of every insertion."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..functions import layout, perm
from ..sources.incidence import segmented
from . import measure


@dataclass
class Nest:
    """The three tables of one set while elements (numbered from 0) are put in.

    ``max_loop`` full turns through the tables are tried for a copy before it is given up."""

    homes: np.ndarray  # slot of element e in table t: homes[t, e]
    slots: int
    max_loop: int
    holder: dict[int, int] = field(default_factory=dict)
    moves: list[int] = field(default_factory=list)
    failed: set[int] = field(default_factory=set)

    def settle(self, element: int) -> int | None:
        """Put one copy in; what it turns out goes on to the next table, in turn. The element that is
        left over when turns run out, else None."""
        here = element
        for step in range(3 * self.max_loop):
            slot = int(self.homes[step % 3, here])
            turned_out = self.holder.get(slot)
            self.holder[slot] = here
            if turned_out is None:
                self.moves.append(step + 1)
                return None
            here = turned_out
        self.moves.append(3 * self.max_loop)
        return here

    def remove(self, element: int) -> None:
        for t in range(3):
            slot = int(self.homes[t, element])
            if self.holder.get(slot) == element:
                del self.holder[slot]

    def insert(self, element: int) -> None:
        """Both copies. If one can't be placed the element is given up, and the copy of
        another element that was left over instead is placed again."""
        waiting = [element, element]
        while waiting:
            copy = waiting.pop()
            if copy in self.failed:
                continue
            left = self.settle(copy)
            if left is not None:
                self.remove(copy)
                self.failed.add(copy)
                if left != copy:
                    waiting.append(left)


def place(x: np.ndarray, log2_r: int, cfg: Config, max_loop: int = 30) -> tuple[np.ndarray, np.ndarray, list[int]]:
    """Slot values of one set of positions ``x``, its failed positions, and the moves of each insertion."""
    codes = np.stack([perm.permute_np(x, t, cfg.segment, cfg.seed) for t in range(3)]).astype(np.int64)
    homes = np.stack([layout.slot_of(codes[t], t, 1 << log2_r, 1 << cfg.r0_bits) for t in range(3)])
    nest = Nest(homes, 3 << log2_r, max_loop)
    for element in range(len(x)):
        nest.insert(element)
    slots = np.zeros(nest.slots, layout.KINDS[cfg.slot_bits])
    for element in range(len(x)):
        held = [t for t in range(3) if nest.holder.get(int(homes[t, element])) == element]
        if len(held) == 2:
            for t, other in (held, held[::-1]):
                slots[homes[t, element]] = layout.encode(codes[t, element], layout.indicator(t, other), cfg)
    return slots, x[sorted(nest.failed)], nest.moves


def transcripts(inc: DataFrame, cfg: Config = Config(), max_loop: int = 30) -> DataFrame:
    """``(steps, insertions, bound)``: how many insertions took ``steps`` moves or more, over all sets, and
    the sum of what the analysis allows (each insertion at most the bound of its set's load). The last row
    (``steps`` null) has the failed insertions and their bound's order."""

    def run(xs: pa.Array) -> pa.Array:
        out = []
        for one in xs:
            x = np.asarray(one.values).astype(np.int64)
            bits = int(layout.range_bits(len(x), cfg))
            _, lost, moves = place(x, bits, cfg, max_loop)
            reached = [int((np.array(moves) >= k).sum()) for k in range(1, max(moves, default=0) + 1)]
            bounds = [len(moves) * measure.transcript_bound(len(x), 1 << bits, k) for k in range(1, 3 * max_loop + 1)]
            out.append({"reached": reached, "bounds": bounds, "lost": len(lost), "order": len(moves) * min(1.0, measure.failure_bound(len(x), 1 << bits))})
        return pa.array(out, pa.struct([("reached", pa.list_(pa.int64())), ("bounds", pa.list_(pa.float64())), ("lost", pa.int64()), ("order", pa.float64())]))

    sets = segmented(inc, cfg.segment).groupBy("item", "seg").agg(F.array_sort(F.collect_set("x")).alias("xs"))
    done = sets.select(F.arrow_udf(run, "reached array<long>, bounds array<double>, lost long, order double")("xs").alias("s")).select("s.*")
    by_step = done.select(F.posexplode("bounds").alias("k", "bound"), "reached")
    steps = by_step.select((F.col("k") + 1).cast("long").alias("steps"), F.coalesce(F.get("reached", F.col("k")), F.lit(0)).alias("n"), "bound")
    steps = steps.groupBy("steps").agg(F.sum("n").alias("insertions"), F.round(F.sum("bound"), 3).alias("bound"))
    lost = done.agg(F.lit(None).cast("long").alias("steps"), F.coalesce(F.sum("lost"), F.lit(0)).alias("insertions"), F.round(F.coalesce(F.sum("order"), F.lit(0.0)), 3).alias("bound"))
    return steps.unionByName(lost)
