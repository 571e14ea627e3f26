"""Rows to the sorted ids of the selectors that they satisfy."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slowlens.functions.bounds import inputs, of_row
from slowlens.functions.literals import token_lookup
from slowlens.functions.measures import Norms
from slowlens.operators.dataset import SubgroupDataset
from slowlens.operators.lattice import signature_columns, signature_of_row
from slowlens.operators.selectors import Selector

DENSE_CHUNK = 200


def selector_ids(selectors: list[Selector]) -> Column:
    """Ids are places in `selectors`. Dense selectors are one native filter over an array, in chunks that compile;
    token selectors look the row's own tokens up in a literal map, so a row costs its non-zero cells only."""
    dense = [(i, s) for i, s in enumerate(selectors) if s.op != "token"]
    parts = []
    for a in range(0, len(dense), DENSE_CHUNK):
        flags = F.array(*[F.when(s.column(), F.lit(i)) for i, s in dense[a : a + DENSE_CHUNK]])
        parts.append(F.filter(flags, lambda x: x.isNotNull()))
    by_map: dict[str, dict[str, list[tuple[int, int]]]] = {}
    for i, s in enumerate(selectors):
        if s.op == "token":
            by_map.setdefault(s.tokens, {}).setdefault(s.value, []).append((int(s.levels[0]) if s.levels else 1, i))
    for name, known in by_map.items():
        lookup = token_lookup(known)
        entries = F.transform(F.filter(F.map_entries(name), lambda e: F.try_element_at(lookup, e["key"]).isNotNull()), lambda e: F.transform(F.filter(F.try_element_at(lookup, e["key"]), lambda x: x["c"] <= e["value"]), lambda x: x["i"]))
        parts.append(F.coalesce(F.flatten(entries), F.array().cast("array<int>")))
    return F.array_sort(F.concat(*parts)) if parts else F.array().cast("array<int>")


def encode(ds: SubgroupDataset, selectors: list[Selector]) -> DataFrame:
    """(oid, t, sels)"""
    return ds.rows().select("oid", "t", selector_ids(selectors).alias("sels"))


def token_map_is_large(selectors: list[Selector], most: int = 200) -> bool:
    return sum(s.op == "token" for s in selectors) > most


def encode_by_index(ds: SubgroupDataset, selectors: list[Selector]) -> DataFrame:
    """As encode(), for more token selectors than a literal should hold: each batch of rows looks its tokens up in a hash
    index of the selectors, beside the scan and without a shuffle."""
    dense = [s for s in selectors if s.op != "token"]
    place = {s: i for i, s in enumerate(selectors)}
    layers: list[dict[str, tuple[int, int]]] = []  # the nth selector of each token
    for s in selectors:
        if s.op == "token":
            layer = next((x for x in layers if s.value not in x), None)
            if layer is None:
                layers.append(layer := {})
            layer[s.value] = (int(s.levels[0]) if s.levels else 1, place[s])
    known = [(list(x), [c for c, _ in x.values()], [i for _, i in x.values()]) for x in layers]

    @F.arrow_udf("array<int>")
    def looked_up(keys: pa.Array, values: pa.Array) -> pa.Array:
        of_row = np.repeat(np.arange(len(keys)), np.diff(np.asarray(keys.offsets)))
        tokens, counts = keys.flatten(), np.asarray(values.flatten())
        rows, found = [], []
        for names, least, ids in known:
            at = np.asarray(pc.fill_null(pc.index_in(tokens, value_set=pa.array(names, tokens.type)), -1))
            hit = np.flatnonzero(at >= 0)
            hit = hit[counts[hit] >= np.array(least)[at[hit]]]
            rows.append(of_row[hit])
            found.append(np.array(ids, np.int32)[at[hit]])
        row, sel = np.concatenate(rows), np.concatenate(found)
        order = np.argsort(row, kind="stable")
        ends = np.searchsorted(row[order], np.arange(len(keys) + 1)).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(sel[order], pa.int32()))

    tokens = F.coalesce(F.col(ds.tokens), F.create_map().cast("map<string,int>"))
    hits = looked_up(F.map_keys(tokens), F.map_values(tokens))
    chunks = [F.filter(F.array(*[F.when(s.column(), F.lit(place[s])) for s in dense[a : a + DENSE_CHUNK]]), lambda x: x.isNotNull()) for a in range(0, len(dense), DENSE_CHUNK)]
    return ds.rows().select("oid", "t", F.array_sort(F.concat(hits, *chunks)).alias("sels"))


def cells(encoded: DataFrame, norms: Norms) -> DataFrame:
    """Rows that satisfy the same selectors are interchangeable for every additive statistic: one row for each such
    group, exact. The log shrinks to its distinct selector sets before any search level reads it."""
    t = F.col("t")
    sums = norms.form.parts(t) | {"s2": (t.cast("double") - norms.mean) * (t.cast("double") - norms.mean)}
    bound = [c.alias(k) for k, c in inputs(t, norms).items()]
    return encoded.groupBy("sels").agg(F.count("*").alias("n"), *[F.sum(c).alias(k) for k, c in sums.items()], *bound, *signature_columns())


def named_rows(ds: SubgroupDataset, dense: list[Selector], norms: Norms) -> DataFrame:
    """As cells, a row for each object, with names in place of ids: the place of a dense selector, `=` and the token for
    a token. Tokens need no list of their own, so they may be as many as the table has."""
    flags = [F.filter(F.array(*[F.when(s.column(), F.lit(str(i))) for i, s in enumerate(dense)][a : a + DENSE_CHUNK]), lambda x: x.isNotNull()) for a in range(0, len(dense), DENSE_CHUNK)]
    held = F.coalesce(F.map_keys(F.map_filter(ds.tokens, lambda k, c: c >= 1)), F.array().cast("array<string>"))
    t = F.col("t")
    sums = {"n": F.lit(1).cast("long")} | norms.form.parts(t) | {"s2": (t.cast("double") - norms.mean) * (t.cast("double") - norms.mean)} | of_row(t, norms) | signature_of_row()
    return ds.rows().select(F.concat(*flags, F.transform(held, lambda k: F.concat(F.lit("="), k))).alias("sels"), *[c.alias(k) for k, c in sums.items()])
