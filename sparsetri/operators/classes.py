"""Exact counts of a graph of large groups, by classes of members instead of pairs.

Members that hold the same set of large groups are one class, and two members share a large group just where their classes do.  So these pairs, dense, are
a matrix of classes and the number of members in each; only pairs of small groups are edges of their own.  All sums are whole numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Classes whose rows of the squared matrix are made together.
ROWS = 256


def matrix(signs: list[list[int]]) -> np.ndarray:
    """Which of the classes, given by their groups, share a group."""
    near, held = np.zeros((len(signs), len(signs)), bool), {}
    for c, groups in enumerate(signs):
        for g in groups:
            held.setdefault(g, []).append(c)
    for own in held.values():
        near[np.ix_(own, own)] = True
    return near


class Classes:
    """A matrix of classes and the members of each, small enough to go to every task."""

    def __init__(self, signs: list[list[int]], members: list[int]):
        self.k, self.bits, self.members = len(signs), np.packbits(matrix(signs)), np.array(members, np.int64)

    def near(self) -> np.ndarray:
        return np.unpackbits(self.bits, count=self.k * self.k).reshape(self.k, self.k).view(bool)

    def around(self) -> list[int]:
        """Of each class the members that share a large group with its own, themselves included."""
        return (self.near() @ self.members).tolist()

    def apart(self):
        """cu, cv among other columns -> the rows whose classes share nothing; a class of -1 has no large group."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            near = self.near()
            for batch in batches:
                cu, cv = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("cu", "cv"))
                both = (cu >= 0) & (cv >= 0)
                keep = ~both
                keep[both] = ~near[cu[both], cv[both]]
                yield batch.filter(pa.array(keep))

        return run

    def squared(self):
        """c, c2, s -> hhh, hhl: of rows with c2 = -1 the ordered triples of members, repeats and all, whose first is in class c and that share pairwise;
        of the others s times the members that share with both classes."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = [tuple(b.column(i).to_numpy(zero_copy_only=False) for i in range(3)) for b in batches if b.num_rows]
            if not rows:
                return
            c, c2, s = (np.concatenate(x) for x in zip(*rows, strict=True))
            near = self.near()
            weighted = near * self.members[:, None].astype(float)
            hhh = hhl = 0
            order = np.argsort(c, kind="stable")
            c, c2, s = c[order], c2[order], s[order]
            own = np.unique(c)
            for k in range(0, len(own), ROWS):
                part = own[k : k + ROWS]
                low, high = np.searchsorted(c, [part[0], part[-1] + 1])
                at = np.searchsorted(part, c[low:high])
                both = near[part].astype(float) @ weighted  # whole numbers below 2^53
                whole = c2[low:high] < 0
                third = ((both * near[part]) @ self.members.astype(float))[at[whole]]
                hhh += sum(int(a) * int(b) for a, b in zip(self.members[c[low:high][whole]], third, strict=True))
                pairs = both[at[~whole], c2[low:high][~whole]]
                hhl += sum(int(a) * int(b) for a, b in zip(s[low:high][~whole], pairs, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([str(hhh)]), pa.array([str(hhl)])], names=["hhh", "hhl"])

        return run

    def between(self):
        """z, wz, c, h (all rows of a z in one task, its neighbours by class) -> hll: wz times the pairs of neighbours of z that share a large group."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = [tuple(b.column(i).to_numpy(zero_copy_only=False) for i in range(4)) for b in batches if b.num_rows]
            if not rows:
                return
            z, wz, c, h = (np.concatenate(x) for x in zip(*rows, strict=True))
            order = np.argsort(z, kind="stable")
            z, wz, c, h = z[order], wz[order], c[order], h[order]
            near, total = self.near(), 0
            first = np.flatnonzero(np.r_[True, z[1:] != z[:-1]])
            for a, b in zip(first.tolist(), [*first[1:].tolist(), len(z)], strict=True):
                own, many = c[a:b], h[a:b]
                pairs = int(many @ (near[np.ix_(own, own)] @ many)) if b - a > 1 else int(many[0]) ** 2
                total += int(wz[a]) * ((pairs - int(many.sum())) // 2)
            yield pa.RecordBatch.from_arrays([pa.array([str(total)])], names=["hll"])

        return run

    def least(self):
        """c, d, n (all rows, in one task: n members of class c have degree d) -> s: the sum of the lesser degree over pairs that share a large group."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = [tuple(b.column(i).to_numpy(zero_copy_only=False) for i in range(3)) for b in batches if b.num_rows]
            if not rows:
                return
            c, d, n = (np.concatenate(x) for x in zip(*rows, strict=True))
            order = np.argsort(-d, kind="stable")
            c, d, n = c[order], d[order], n[order]
            near, above, total = self.near(), np.zeros(self.k, np.int64), 0
            first = np.flatnonzero(np.r_[True, d[1:] != d[:-1]])
            for a, b in zip(first.tolist(), [*first[1:].tolist(), len(d)], strict=True):
                own, many = c[a:b], n[a:b]
                more = int(many @ (near[own] @ above))
                same = (int(many @ (near[np.ix_(own, own)] @ many)) - int(many.sum())) // 2
                total += int(d[a]) * (more + same)
                above[own] += many
            yield pa.RecordBatch.from_arrays([pa.array([str(total)])], names=["s"])

        return run
