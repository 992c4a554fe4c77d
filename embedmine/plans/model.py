"""What an application tells the engine."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.canonical import words


@dataclass(frozen=True)
class EmbeddingView:
    """Columns of an embedding as the user functions see it; ``size`` words."""

    size: int
    mode: str
    columns: tuple[str, ...]

    @property
    def words(self) -> list[Column]:
        return [F.col(w) for w in words(self.size)]

    @property
    def first(self) -> Column:
        return F.col("w0")

    @property
    def smallest(self) -> Column:
        return F.col("w0")  # a canonical embedding starts at its smallest word

    @property
    def code(self) -> Column:
        return F.col("code")

    @property
    def touch(self) -> Column:
        """Bit i: the newest word touches word i (vertex mode, from size 2 on)."""
        return F.col("touch")

    @property
    def visited(self) -> Column:
        """The embedding's vertices by first visit, as its quick code numbers them."""
        return self.array() if self.mode == "vertex" else F.col("vs")

    @property
    def n_vertices(self) -> Column:
        return F.lit(self.size) if self.mode == "vertex" else F.size("vs")

    @property
    def n_edges(self) -> Column:
        return F.bit_count("code") if self.mode == "vertex" else F.lit(self.size)

    @property
    def is_clique(self) -> Column:
        """The newest vertex touches all others; with the parent a clique, the whole is one."""
        return F.lit(True) if self.size == 1 else F.bit_count("touch") == self.size - 1

    @property
    def labels(self) -> Column:
        return F.col("labels")

    def array(self) -> Column:
        return F.array(*self.words)


#: Keys of emitted values: a column, or PATTERN for the embedding's canonical pattern.
PATTERN = "pattern"


@dataclass(frozen=True)
class Emit:
    """A value mapped to a key. ``reduce``: aggregate of ``value`` over the embeddings of a key;
    ``merge``: aggregate that joins partial results. ``when``: "end" or "step" (output aggregation only)."""

    name: str
    key: str | Callable[[EmbeddingView], Column]
    value: Callable[[EmbeddingView], Column]
    reduce: Callable[[Column], Column] = F.sum
    merge: Callable[[Column], Column] = F.sum
    when: str = "end"


@dataclass(frozen=True)
class Domains:
    """A mapped value of another kind, keyed by pattern: the embedding's vertices, each for its place in the
    pattern. Reduced by union place by place (of an orbit, since symmetric places have one domain); what is
    read is the size of the smallest union. ``least``: sizes below it need not be known."""

    name: str = "support"
    least: int | None = None
    key: str = PATTERN


@dataclass(frozen=True)
class MiningApp:
    """A filter-process application.

    filter: is a candidate processed (anti-monotone, the same for automorphic
    embeddings). output: columns written for each processed embedding.
    maps: values aggregated in the step, readable in the next. map_outputs:
    values aggregated for the result only. aggregation_filter(view, read):
    whether an embedding is expanded, given the aggregates of its step;
    aggregation_output(view, read): columns written then. termination: stops an
    embedding after it was processed. ``read(name)`` is the column of an
    aggregate of the embedding's key. labelled: vertex labels in vertex-mode
    patterns; labels: which labels edge-mode patterns have ("vertex", "edge", "both").
    needs: columns of the newest vertex or edge that the functions read beside those of
    the view, as a DataFrame keyed by ``word`` (degrees, attributes); joined to the candidates.
    counted: filter and termination depend on the size alone, keys and values on the first word and the quick
    code, and values are summed; then steps of up to three vertices may be counted instead of generated.
    """

    name: str
    mode: str = "vertex"
    labelled: bool = False
    labels: str = "both"
    needs: DataFrame | None = None
    filter: Callable[[EmbeddingView], Column] = lambda e: F.lit(True)
    output: Callable[[EmbeddingView], list[Column]] | None = None
    maps: tuple[Emit | Domains, ...] = ()
    map_outputs: tuple[Emit, ...] = ()
    aggregation_filter: Callable[[EmbeddingView, Callable[[str], Column]], Column] | None = None
    aggregation_output: Callable[[EmbeddingView, Callable[[str], Column]], list[Column]] | None = None
    termination: Callable[[EmbeddingView], Column] | None = None
    max_size: int | None = None
    counted: bool = False


@dataclass
class MiningResult:
    """outputs: by step; aggregates: by (step, name); finals: by name; funnel: rows of counts by step;
    levels: the embeddings kept at each step."""

    outputs: dict[int, DataFrame] = field(default_factory=dict)
    late_outputs: dict[int, DataFrame] = field(default_factory=dict)
    aggregates: dict[tuple[int, str], DataFrame] = field(default_factory=dict)
    finals: dict[str, DataFrame] = field(default_factory=dict)
    levels: dict[int, DataFrame] = field(default_factory=dict)
    funnel: list[dict] = field(default_factory=list)
