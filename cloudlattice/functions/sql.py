"""SQL functions: ``register(spark)`` makes them temporary functions of the session, inlined by the optimizer."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="key bigint, n bigint")
class DecodeChunk:
    """Keys and counts of a container row: ``SELECT c.part, d.* FROM chunks c, LATERAL decode_chunk(key_first, n_points, n_cells, rle, cell_blob, count_blob) d``."""

    def eval(self, key_first: int, n_points: int, n_cells: int, rle: bool, cell_blob: bytes, count_blob: bytes) -> Iterator[tuple[int, int]]:
        from cloudlattice.operators.container import decode_chunk

        row = {"key_first": key_first, "n_points": n_points, "n_cells": n_cells, "rle": rle, "cell_blob": bytes(cell_blob), "count_blob": count_blob and bytes(count_blob)}
        key, n = decode_chunk(row)
        yield from zip(key.tolist(), n.tolist(), strict=True)


def register(spark: SparkSession) -> list[str]:
    """to_cell, cell_center, morton (12 bits an axis; larger or negative coordinates are an error), morton_part, exp_golomb_bits; table function decode_chunk."""
    floor = {c: f"floor({c} * sqrt(5D) / (2 * eps))" for c in "xyz"}
    even = {c: f"({f} + pmod({f}, 2))" for c, f in floor.items()}
    odd = {c: f"({f} + 1 - pmod({f}, 2))" for c, f in floor.items()}
    gap = lambda p: " + ".join(f"pow({c} * sqrt(5D) / (2 * eps) - {p[c]}, 2)" for c in "xyz")
    pick = ", ".join(f"'{n}', cast(CASE WHEN {gap(even)} <= {gap(odd)} THEN {even[c]} ELSE {odd[c]} END AS BIGINT)" for n, c in zip("ijk", "xyz", strict=True))
    bits = " | ".join(f"shiftleft(shiftright({c}, {b}) & 1L, {3 * b + a})" for b in range(12) for a, c in enumerate("ijk"))
    part = " | ".join(f"shiftleft(shiftright(code, {3 * b} + axis) & 1L, {b})" for b in range(12))
    functions = {
        "to_cell(x DOUBLE, y DOUBLE, z DOUBLE, eps DOUBLE)": ("STRUCT<i: BIGINT, j: BIGINT, k: BIGINT>", f"named_struct({pick})"),
        "cell_center(cell STRUCT<i: BIGINT, j: BIGINT, k: BIGINT>, eps DOUBLE)": ("STRUCT<x: DOUBLE, y: DOUBLE, z: DOUBLE>", f"named_struct({', '.join(f"'{c}', cell.{n} * 2 * eps / sqrt(5D)" for n, c in zip('ijk', 'xyz', strict=True))})"),
        "morton(i BIGINT, j BIGINT, k BIGINT)": ("BIGINT", f"CASE WHEN least(i, j, k) < 0 OR greatest(i, j, k) > 4095 THEN raise_error('morton takes 12 bits an axis; larger coordinates go through the curves module') ELSE {bits} END"),
        "morton_part(code BIGINT, axis INT)": ("BIGINT", part),
        "exp_golomb_bits(n BIGINT, o INT)": ("INT", "2 * (length(bin(shiftright(n, o) + 1)) - 1) + 1 + o"),
    }
    for head, (kind, body) in functions.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")
    spark.udtf.register("decode_chunk", DecodeChunk)
    return [*(h.split("(")[0] for h in functions), "decode_chunk"]
