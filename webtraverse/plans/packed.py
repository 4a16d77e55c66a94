"""A subweb as arrays, for cells of many documents: the URIs that a query may queue are numbers, and a document is a slice.

What a query reaches is known before it runs, as far as URIs go: only those of matching triples, and its seeds, can ever be queued. Links to others
count for nothing but PageRank, whose known graph has them as vertices.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable

import numpy as np

from .query import ConjunctiveQuery, Lit, Var

#: Triples whose links are sorted at once.
CHUNK = 200_000


class PackedWeb:
    """Triples (s, p, o) of documents as sorted arrays; an object that is no URI is negative."""

    def __init__(self, docs: np.ndarray, doc: np.ndarray, s: np.ndarray, p: np.ndarray, o: np.ndarray):
        order = np.lexsort((o, p, s, doc))
        self.docs, self.doc, self.s, self.p, self.o = np.unique(docs), doc[order], s[order], p[order], o[order]
        self.readers: dict[ConjunctiveQuery, PackedReader] = {}

    @classmethod
    def of_batches(cls, batches: Iterable) -> "PackedWeb":
        """From Arrow batches (doc, s, p, o), each let go before the next; a document without triples is a row without ``s``."""
        parts: list[tuple] = []
        for batch in batches:
            doc, s, p, o = (batch.column(c) for c in ("doc", "s", "p", "o"))
            has = s.is_valid().to_numpy(zero_copy_only=False)
            every = doc.to_numpy(zero_copy_only=False)
            held = [c.fill_null(0).to_numpy(zero_copy_only=False)[has] for c in (s, p, o)]
            parts.append((every[~has].copy(), every[has], held[0], held[1].astype(np.int32), held[2]))
            del batch, doc, s, p, o, every, held
        columns = []
        for k, kind in enumerate((np.int64, np.int64, np.int64, np.int32, np.int64)):
            columns.append(np.concatenate([part[k] for part in parts]) if parts else np.empty(0, kind))
            parts = [(*part[:k], None, *part[k + 1 :]) for part in parts]
        bare, doc, s, p, o = columns
        return cls(np.concatenate([bare, np.unique(doc)]), doc, s, p, o)

    def reader(self, query: ConjunctiveQuery, graph: str, every: bool) -> "PackedReader":
        """``every``: vertices that can't be queued count, too."""
        held = self.readers.get(query)
        if held is None:
            held = self.readers[query] = PackedReader(self, query)
        held.linked(graph, every)
        return held


class PackedReader:
    """What a query sees of a subweb, by number."""

    def __init__(self, web: PackedWeb, query: ConjunctiveQuery):
        self.web, self.query = web, query
        masks = np.zeros(len(web.s), np.int32)
        columns = {"s": web.s, "p": web.p, "o": web.o}
        for i, t in enumerate(query.patterns):
            hit = np.ones(len(web.s), bool)
            for term, c in ((t.s, "s"), (t.p, "p"), (t.o, "o")):
                if not isinstance(term, Var):
                    value = term.value if isinstance(term, Lit) else term
                    hit &= columns[c] == value if isinstance(value, (int, float)) else False
            for places in t.places().values():
                if len(places) > 1:
                    ids = [columns[c].astype(np.int64) * 16 if c == "p" else columns[c] for c in places]
                    for other in ids[1:]:
                        hit &= ids[0] == other
            masks |= hit.astype(np.int32) << i
        self.matched = masks != 0
        rows = np.flatnonzero(masks)
        s, p, o = web.s[rows], web.p[rows].astype(np.int64) * 16, web.o[rows]
        #: URIs that may be queued, by number.
        self.names = np.unique(np.concatenate([np.array(query.seeds(), np.int64), np.unique(s), np.unique(p), np.unique(o[o >= 0])]))
        self.queueable = self.size = len(self.names)
        self.ints = list(range(self.size))  # one object for each number
        self.here = bytearray(np.isin(self.names, web.docs, assume_unique=True).tobytes())
        owner, held = self._numbers(web.doc[rows])
        literal = np.flatnonzero(o < 0)
        self.literals, code = np.unique(o[literal], return_inverse=True)
        o = np.where(o < 0, -1, self._numbers(o)[0])
        o[literal] = -1 - code
        self.hit_s, self.hit_p, self.hit_o, self.hit_mask = (x[held].astype(np.int32) for x in (self._numbers(s)[0], self._numbers(p)[0], o, masks[rows]))
        self.hit_at = self._bounds(owner[held])
        self.spots = [tuple("spo".index(t.places()[v][0]) if v in t.places() else None for v in query.variables) for t in query.patterns]
        self.how = {m: [(i, self.spots[i]) for i in range(query.n) if m >> i & 1] for m in np.unique(self.hit_mask).tolist()}
        self.links_of: dict[tuple[str, bool], tuple] = {}
        self.link_at = self.link_to = None

    def _numbers(self, uris: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Numbers, and which of them are right: the others are no URIs that may be queued."""
        i = np.searchsorted(self.names, uris)
        i[i == len(self.names)] = 0
        return i, self.names[i] == uris if len(self.names) else np.zeros(len(uris), bool)

    def _bounds(self, owner: np.ndarray) -> np.ndarray:
        out = np.zeros(self.queueable + 1, np.int64)
        np.cumsum(np.bincount(owner, minlength=self.queueable), out=out[1:])
        return out

    def linked(self, graph: str, every: bool) -> None:
        """Make the distinct links of each document ready, in scanning order: all, or to what may be queued."""
        found = self.links_of.get((graph, every))
        if found is None:
            found = self.links_of[graph, every] = self._links(graph, every)
        self.link_at, self.link_to, self.size = found

    def _links(self, graph: str, every: bool) -> tuple[np.ndarray, np.ndarray, int]:
        web, size = self.web, self.queueable
        rest = np.empty(0, np.int64)
        if every:
            rest = np.unique(np.concatenate([np.unique(web.s), np.unique(web.p).astype(np.int64) * 16, np.unique(web.o[web.o >= 0])]))
            rest = rest[~np.isin(rest, self.names, assume_unique=True)]
            size += len(rest)
        owners, parts, start = [], [], 0
        while start < len(web.doc):
            end = min(len(web.doc), start + CHUNK)
            if end < len(web.doc):  # all of the last document
                end = int(np.searchsorted(web.doc, web.doc[end - 1], "right"))
            rows = slice(start, end)
            start = end
            owner, held = self._numbers(web.doc[rows])
            flat = np.stack([web.s[rows], web.p[rows].astype(np.int64) * 16, web.o[rows]], axis=1)
            if graph != "all":
                held &= self.matched[rows]
            owner, flat = np.repeat(owner[held], 3), flat[held].ravel()
            to, known = self._numbers(flat)
            if every:
                to[~known] = self.queueable + np.searchsorted(rest, flat[~known])
                known = flat >= 0
            known &= to != owner
            owner, to = owner[known], to[known]
            _, first = np.unique(owner * np.int64(max(size, 1)) + to, return_index=True)
            first.sort()
            owners.append(owner[first].astype(np.int32))
            parts.append(to[first].astype(np.int32))
        at = self._bounds(np.concatenate(owners) if owners else np.empty(0, np.int32))
        return at, np.concatenate(parts) if parts else np.empty(0, np.int32), size

    def seeds(self) -> list[int]:
        return [self.ints[i] for i in np.searchsorted(self.names, np.array(self.query.seeds(), np.int64)).tolist()]

    def lookup(self, u: int) -> int | None:
        return u if self.here[u] else None

    def hits(self, u: int) -> list[tuple]:
        """Matching triples in scanning order: (triple, URIs, [(pattern, values of all variables)])."""
        rows = slice(self.hit_at[u], self.hit_at[u + 1])
        ints, out = self.ints, []
        for s, p, o, mask in zip(self.hit_s[rows].tolist(), self.hit_p[rows].tolist(), self.hit_o[rows].tolist(), self.hit_mask[rows].tolist()):
            triple = (ints[s], ints[p], ints[o] if o >= 0 else o)
            out.append((triple, triple if o >= 0 else triple[:2], [(i, tuple(None if k is None else triple[k] for k in spots)) for i, spots in self.how[mask]]))
        return out

    def links(self, u: int) -> np.ndarray:
        return self.link_to[self.link_at[u] : self.link_at[u + 1]]

    def linkers(self) -> Callable[[int], np.ndarray]:
        """Documents with a link to a URI, by its number."""
        owner = np.repeat(np.arange(self.queueable, dtype=np.int32), np.diff(self.link_at))
        inner = self.link_to < self.queueable
        owner, to = owner[inner], self.link_to[inner]
        by, at = owner[np.argsort(to, kind="stable")], self._bounds(to)
        return lambda u: by[at[u] : at[u + 1]]

    def name(self, u: int) -> int:
        return int(self.names[u]) if u >= 0 else int(self.literals[-1 - u])
