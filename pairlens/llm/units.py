"""Token ids of whole texts through a memo of units.

A text is cut before a single space that stands between two characters that are surely not white space. Neither the
byte-level pattern nor a piece model without inner word marks joins anything across such a cut, so a text's tokens are
those of its units one after the other. Units are told apart by 64-bit hashes over the bytes (see textkernel); each
unit that a worker has not met is encoded once by the library, in batches balanced by bytes.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from pairlens.llm.textkernel import mix, running, span_hash

#: Units that a worker remembers at most; beyond that the memo starts anew (results are the same).
MEMO_UNITS = 2_000_000
#: First bytes of characters that may be white space beyond ASCII.
WIDE = np.zeros(256, bool)
WIDE[[0xC2, 0xE1, 0xE2, 0xE3]] = True


def cut_points(data: np.ndarray) -> np.ndarray:
    """Positions of spaces before which a text may be cut safely."""
    at = np.flatnonzero(data == 32)
    at = at[(at >= 3) & (at + 1 < len(data))]
    before, after = data[at - 1], data[at + 1]
    ok = (before > 32) & (before != 127) & (after > 32) & (after != 127) & ~WIDE[after]
    ok &= ~((before >= 128) & (WIDE[data[at - 2]] | WIDE[data[at - 3]]))
    return at[ok]


class UnitMemo:
    """encode(units as str, without the space they start with; whether they start their text) -> ids of each as bytes.

    What is known stands in a few sorted arrays, each several times larger than the next (about 30 bytes a unit), so a
    worker's memo stays small and is not copied for each batch.
    """

    def __init__(self, encode: Callable[[list[str], bool], list[bytes]], batch_bytes: int = 1 << 18):
        self.encode, self.batch_bytes = encode, batch_bytes
        self.clear()

    def clear(self) -> None:
        self.levels: list[tuple[np.ndarray, np.ndarray]] = []
        self.ids, self.used = np.zeros(1 << 16, "<u4"), 0

    def learn(self, keys: np.ndarray, units: list[bytes], leading: bool) -> None:
        got, at = [], 0
        while at < len(units):
            end, size = at, 0
            while end < len(units) and (end == at or size + len(units[end]) <= self.batch_bytes):
                size += len(units[end])
                end += 1
            got += self.encode([u.decode("utf-8", "replace") for u in units[at:end]], leading)
            at = end
        if not got:
            return
        n = np.array([len(x) for x in got], np.int64) // 4
        end = self.used + int(n.sum())
        if end > len(self.ids):
            self.ids = np.concatenate([self.ids[: self.used], np.zeros(2 * end - self.used, "<u4")])
        self.ids[self.used : end] = np.frombuffer(b"".join(got), "<u4")
        self.levels.append((keys, np.stack([self.used + np.cumsum(n) - n, n], 1)))
        self.used = end
        while len(self.levels) > 1 and 3 * len(self.levels[-1][0]) >= len(self.levels[-2][0]):
            (k, p), (kk, pp) = self.levels.pop(), self.levels.pop()
            k, p = np.concatenate([kk, k]), np.concatenate([pp, p])
            order = np.argsort(k, kind="stable")
            self.levels.append((k[order], p[order]))

    def places(self, keys: np.ndarray) -> np.ndarray:
        """(place, number) of each key's ids; -1 for those not known."""
        out = np.full((len(keys), 2), -1, np.int64)
        for k, p in self.levels:
            i = np.minimum(np.searchsorted(k, keys), len(k) - 1)
            hit = k[i] == keys
            out[hit] = p[i[hit]]
        return out

    def __call__(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, bounds of each text in them)."""
        sizes = np.array([len(t) for t in texts], np.int64)
        at = np.concatenate([[0], np.cumsum(sizes + 1)])
        raw = b"\n".join(texts) + b"\n"
        data = np.frombuffer(raw, np.uint8)
        starts = np.sort(np.concatenate([cut_points(data), at[:-1]]))
        ends = np.concatenate([starts[1:], [len(data)]])
        leading = np.zeros(len(starts), bool)
        first = np.searchsorted(starts, at)
        leading[first[:-1]] = True
        ends[first[1:] - 1] = at[1:] - 1
        body = starts + ~leading  # without the space that a later unit starts with
        h = mix(span_hash(running(data), body, ends) + leading.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        order = np.argsort(h)
        is_new = np.concatenate([[True], np.diff(h[order]) != 0]) if len(h) else np.zeros(0, bool)
        kinds, where = h[order[is_new]], order[is_new]
        back = np.empty(len(h), np.int64)
        back[order] = np.cumsum(is_new) - 1
        if sum(len(k) for k, _ in self.levels) > MEMO_UNITS:
            self.clear()
        new = self.places(kinds)[:, 0] < 0
        for lead in (False, True):
            own = new & (leading[where] == lead)
            w = where[own]
            self.learn(kinds[own], [raw[a:b] for a, b in zip(body[w].tolist(), ends[w].tolist(), strict=True)], lead)
        place = self.places(kinds)[back]
        n = place[:, 1]
        total = np.concatenate([[0], np.cumsum(n)])
        ids = self.ids[np.arange(total[-1]) + np.repeat(place[:, 0] - total[:-1], n)]
        return ids, total[first]
