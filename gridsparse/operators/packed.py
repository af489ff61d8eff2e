"""Column look-ups in packed blocks, with array functions inside the rows of ``layout.pack_dcsc``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators.layout import Grid
from gridsparse.storage import small


def _lower_bound(j: str) -> str:
    """SQL: the first place in jc whose column is not below ``j``, by halving."""
    mid = "cast((s.lo + s.hi) div 2 as int)"
    step = f"if(s.lo < s.hi and get(jc, {mid}) < {j}, struct({mid} + 1 as lo, s.hi as hi), struct(s.lo as lo, if(s.lo < s.hi, {mid}, s.hi) as hi))"
    return f"aggregate(sequence(1, cast(ceil(log2(size(jc) + 1)) as int)), struct(0 as lo, size(jc) as hi), (s, x) -> {step}, s -> s.lo)"


def _near(j: str, width: int) -> str:
    """SQL: the same place by the block's aux: a scan of the columns of one short range, one column on average."""
    k = f"cast(({j} - bc * {width}L) div greatest(1, {width}L div size(jc)) as int)"
    low, high = f"cast(get(aux, {k}) as int)", f"cast(coalesce(get(aux, {k} + 1), size(jc)) as int)"
    return f"{low} + size(filter(slice(jc, {low} + 1, {high} - {low}), x -> x < {j}))"


def _entries(places: str) -> str:
    """SQL: the entries of the columns at ``places``, one array."""
    return f"flatten(transform({places}, c -> transform(sequence(cp[c], cp[c + 1] - 1), e -> struct(ir[cast(e as int)] as i, jc[c] as j, num[cast(e as int)] as v))))"


def _unfold(found: DataFrame, places: str, shape: tuple[int, int]) -> SparseMatrix:
    return SparseMatrix(found.select(F.explode(F.expr(_entries(places))).alias("e")).select("e.i", "e.j", "e.v"), *shape)


def columns(packed: DataFrame, wanted: DataFrame, shape: tuple[int, int], grid: Grid, aux: bool = True) -> SparseMatrix:
    """The entries of the columns that ``wanted`` (j) names; absent and empty columns give none, repeats count once.

    Each block is met once, with the list of its wanted columns.  ``aux`` uses
    the block's look-up array (``pack_dcsc(..., aux=True)``), otherwise its
    nonempty columns are searched by halving.
    """
    width = max(1, -(-shape[1] // grid.pc))
    inside = wanted.select(F.col("j").cast("long").alias("j")).where(F.col("j").between(0, shape[1] - 1)).distinct()
    lists = inside.groupBy(F.floor(F.col("j") / width).cast("int").alias("bc")).agg(F.collect_list("j").alias("js"))
    at = _near("j", width) if aux else _lower_bound("j")
    met = packed.join(small(lists), "bc")
    met = met.withColumn("places", F.expr(f"filter(transform(js, j -> struct(j as j, {at} as c)), p -> get(jc, p.c) = p.j).c"))
    return _unfold(met, "places", shape)


def column_range(packed: DataFrame, low: int, high: int, shape: tuple[int, int], grid: Grid) -> SparseMatrix:
    """The entries of columns ``low`` to ``high - 1``: two searches in each block that the range meets, and what lies between."""
    width = max(1, -(-shape[1] // grid.pc))
    met = packed.where(F.col("bc").between(low // width, (high - 1) // width))
    met = met.withColumn("first", F.expr(_lower_bound(f"{low}L"))).withColumn("last", F.expr(_lower_bound(f"{high}L"))).where("first < last")
    return _unfold(met, "sequence(first, last - 1)", shape)
