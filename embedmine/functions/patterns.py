"""Patterns: quick codes read off in visiting order, and their canonical forms.

Canonical forms are computed for distinct quick codes only. Vertices are
coloured by label and degree, colours refined by those of the neighbours until
nothing changes; ties are broken by trying the vertices of the first open
colour, of twins one only. The smallest relabelled form is the canonical one; the
labellings that attain it, and the twins, give the orbits.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame

cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: canon: text of the form; positions: place of each visited vertex in it; orbit: the least place of its orbit.
CANON = "canon string, k int, n_edges int, degs string, lbls string, positions array<int>, orbit array<int>"


def vertex_pattern(code: int, k: int, labels: list[int] | None) -> tuple:
    """A vertex-mode code as (vertex labels, edges (i, j, label))."""
    edges, at = [], 0
    for i in range(1, k):
        edges += [(j, i, 0) for j in range(i) if code >> (at + j) & 1]
        at += i
    return tuple(labels or [0] * k), tuple(edges)


def edge_pattern(code: str) -> tuple:
    """An edge-mode code "0-1:e,1-2:e|labels" as (vertex labels, edges)."""
    edges, labels = code.split("|")
    parts = [e.split(":") for e in edges.split(",")]
    return tuple(map(int, labels.split(","))), tuple((*sorted(map(int, ends.split("-"))), int(label)) for ends, label in parts)


#: Forms already computed in this process, up to MEMO of them.
MEMO = 100_000
_known: dict[tuple, tuple] = {}


def canonical(labels: tuple[int, ...], edges: tuple[tuple[int, int, int], ...]) -> tuple:
    """(form, positions, orbits) of a pattern, remembered across steps."""
    key = (labels, edges)
    if key not in _known:
        if len(_known) >= MEMO:
            _known.clear()
        _known[key] = compute_canonical(labels, edges)
    return _known[key]


def compute_canonical(labels: tuple[int, ...], edges: tuple[tuple[int, int, int], ...]) -> tuple:
    n = len(labels)
    near: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for a, b, e in edges:
        near[a].append((e, b))
        near[b].append((e, a))

    def ranks(keys: list) -> list[int]:
        order = {k: i for i, k in enumerate(sorted(set(keys)))}
        return [order[k] for k in keys]

    def refine(colours: list[int]) -> list[int]:
        while True:
            new = ranks([(colours[v], tuple(sorted((e, colours[u]) for e, u in near[v]))) for v in range(n)])
            if max(new, default=0) == max(colours, default=0):
                return new
            colours = new

    best: list = [None, []]

    def around(u: int, v: int) -> list[tuple[int, int]]:
        return sorted((e, w) for e, w in near[u] if w != v)

    # Twins have the same label and neighbours, so that exchanging them changes nothing: one of them is tried.
    twins = [[u for u in range(v) if labels[u] == labels[v] and around(u, v) == around(v, u)] for v in range(n)]

    def search(colours: list[int]) -> None:
        cells: dict[int, list[int]] = {}
        for v, c in enumerate(colours):
            cells.setdefault(c, []).append(v)
        open_ = next((c for c in sorted(cells) if len(cells[c]) > 1), None)
        if open_ is None:
            form = (tuple(labels[v] for v in sorted(range(n), key=colours.__getitem__)), tuple(sorted((*sorted((colours[a], colours[b])), e) for a, b, e in edges)))
            if best[0] is None or form < best[0]:
                best[:] = [form, [colours]]
            elif form == best[0]:
                best[1].append(colours)
            return
        cell = cells[open_]
        for v in cell:
            if not any(u in cell for u in twins[v]):
                search(refine(ranks([(c, u != v) if c == open_ else (c, True) for u, c in enumerate(colours)])))

    search(refine(ranks([(labels[v], len(near[v])) for v in range(n)])))
    form, found = best
    # Two labellings of one form make a symmetry, and so do twins; together they give the orbits.
    least = list(range(n))  # by place in the form
    at = found[0]
    pairs = [(at[v], lab[v]) for lab in found for v in range(n)] + [(at[u], at[v]) for v in range(n) for u in twins[v]]
    while True:
        before = list(least)
        for x, y in pairs:
            least[x] = least[y] = min(least[x], least[y])
        if least == before:
            break
    return form, tuple(at), tuple(least[p] for p in at)


def isomorphic(a: tuple, b: tuple) -> bool:
    return canonical(*a)[0] == canonical(*b)[0]


def spelled(form: tuple) -> str:
    labels, edges = form
    return ",".join(f"{a}-{b}:{e}" for a, b, e in edges) + "|" + ",".join(map(str, labels))


def described(labels: tuple, edges: tuple, fresh: bool = False) -> tuple:
    """The columns of CANON; ``fresh`` computes the form anew."""
    form, positions, orbit = (compute_canonical if fresh else canonical)(labels, edges)
    degree = [0] * len(labels)
    for a, b, _ in edges:
        degree[a] += 1
        degree[b] += 1
    return spelled(form), len(labels), len(edges), "-".join(map(str, sorted(degree))), "|".join(map(str, sorted(labels))), list(positions), list(orbit)


def canonicalize(codes: DataFrame, k: int | None = None, grouped: bool = False) -> DataFrame:
    """Distinct quick codes with their canonical forms: (code long[, labels]) of k vertices, or in
    edge mode (code, labels) as texts. ``grouped``: the codes are distinct already, all columns stay."""
    labelled = "labels" in codes.columns
    if not grouped:
        codes = codes.select("code", *(["labels"] if labelled else [])).distinct()
    columns = codes.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = batch.column(columns.index("labels")).to_pylist() if labelled else [None] * batch.num_rows
            of = zip(batch.column(columns.index("code")).to_pylist(), marks)
            forms = [described(*(edge_pattern(f"{c}|{m}") if k is None else vertex_pattern(c, k, m))) for c, m in of]
            kinds = [pa.string(), pa.int32(), pa.int32(), pa.string(), pa.string(), pa.list_(pa.int32()), pa.list_(pa.int32())]
            yield pa.RecordBatch.from_arrays([*batch.columns, *[pa.array([f[i] for f in forms], t) for i, t in enumerate(kinds)]], names=[*columns, "canon", "k", "n_edges", "degs", "lbls", "positions", "orbit"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in codes.schema.fields)
    return codes.mapInArrow(run, f"{schema}, {CANON}")
