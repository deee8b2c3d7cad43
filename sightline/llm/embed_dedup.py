"""Near duplicates among embeddings by search in a robust-pruned flat graph, verified in double precision."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import graph
from .common import connected_components, saved

#: Vectors of a region: one graph, built and searched in one task.
REGION_ROWS = 6000
#: Queries that one task answers.
QUERY_ROWS = 12_000


def _sound() -> F.Column:
    v = F.col("embedding")
    return (
        v.isNotNull() & F.col("label").isNotNull() & F.col("vec_id").isNotNull()
        & F.forall(v, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf"))) & F.exists(v, lambda e: e != 0)
    )


def _valid(vectors: DataFrame) -> DataFrame:
    return vectors.where(_sound())


def _regions(nodes: DataFrame, rows: int, sample: int, seed: int) -> dict[tuple, np.ndarray]:
    """Centres of the regions of each label (and vector length) with more than ``rows`` nodes, from ``sample`` of its nodes by hash."""
    large = nodes.groupBy("label", "dim").agg(F.count("*").alias("n")).where(F.col("n") > rows)
    place = F.row_number().over(Window.partitionBy("label", "dim").orderBy(F.xxhash64(F.lit(seed), "rep"), "rep"))
    few = nodes.join(F.broadcast(large), ["label", "dim"]).withColumn("place", place).where(F.col("place") <= sample)  # at most one row for each ``rows`` nodes

    def centres(pdf: pd.DataFrame) -> pd.DataFrame:
        pool = np.stack(pdf.sort_values("place")["unit"].to_list())
        k = min(-(-int(pdf["n"].iloc[0]) // rows), len(pool))
        _, medoids = graph.clusters(pool, max(1, len(pool) // k), 1, seed)
        return pd.DataFrame({"label": pdf["label"].iloc[0], "dim": pdf["dim"].iloc[0], "centre": list(pool[np.unique(medoids)[:k]])})

    kind = nodes.schema["label"].dataType.simpleString()
    found = few.groupBy("label", "dim").applyInPandas(centres, f"label {kind}, dim int, centre array<double>").collect()  # regions, at most ``sample`` a label
    out: dict[tuple, list] = {}
    for r in found:
        out.setdefault((r.label, r.dim), []).append(r.centre)
    return {k: np.array(v) for k, v in out.items()}


def near_vectors(vectors: DataFrame, least: float = 0.93, region_rows: int = REGION_ROWS, query_rows: int = QUERY_ROWS, sample: int = 4096, audit_rows: int = 2000) -> tuple[DataFrame, float]:
    """Per row of ``vectors`` (vec_id, embedding, label): vec_id, n_links, component_id, kept; and the recall of the audit.

    Vectors link when labels and lengths are equal, labels are not null and the cosine is at least ``least`` in double precision. Null and zero vectors,
    and those with null or non-finite components, have no links. Equal vectors of a label are one node with a weight, so
    copies cost nothing. Labels of more than ``region_rows`` nodes are split in regions around centres from a bounded sample; a region that is
    larger, for a hot spot, is split by hash. A task builds the graph of a region part (shards with overlap, robust pruning, union of lists),
    and searches it for each of its own nodes. A node also looks into every other region that may hold a link of it: where its angle to the
    region's centre is no more than the region's widest (and no less than its narrowest) plus the angle of ``least``; by the triangle inequality no
    other region can. These searches join blocks of queries with the stored graphs. All hits are verified in double precision; what comes out are link
    counts and a spanning forest of the links, never all pairs. The audit compares at most ``audit_rows`` nodes whose id is
    divisible by 20 (by hash) with all nodes of their label and returns found / true links (1 without links; 0 rows: no audit, 1).
    Rows with equal vec_id count as one vector each time they occur. Empty tables give no rows.
    """
    spark: SparkSession = vectors.sparkSession
    base = vectors.select("vec_id", "embedding", "label")
    kind, id_kind = (base.schema[c].dataType.simpleString() for c in ("label", "vec_id"))
    unit = F.transform("embedding", lambda e: e.cast("double"))
    norm = F.sqrt(F.aggregate(unit, F.lit(0.0), lambda a, e: a + e * e))
    sound = _valid(base)
    # rows with the same label and the very same numbers are one node
    nodes = sound.groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"))
    nodes = saved(nodes.withColumns({"unit": F.transform(unit, lambda e: e / norm), "dim": F.size("embedding")}), "vectors")
    centres = _regions(nodes, region_rows, sample, 3)
    reach = float(np.arccos(least)) + 1e-6
    if centres:
        held = spark.sparkContext.broadcast(centres)

        @F.pandas_udf("struct<home int, angle double>")
        def nearest(label: pd.Series, dim: pd.Series, units: pd.Series) -> pd.DataFrame:
            return pd.DataFrame([_home(held.value.get((k, d)), u) for k, d, u in zip(label.tolist(), dim.tolist(), units)], columns=["home", "angle"])

        placed = saved(nodes.withColumn("at", nearest("label", "dim", "unit")).select("*", "at.home", "at.angle").drop("at"), "placed-vectors")
    else:
        placed = nodes.withColumns({"home": F.lit(0), "angle": F.lit(0.0)})
    key = ["label", "dim", "home"]
    sizes = placed.groupBy(*key).agg(F.ceil(F.count("*") / (1.5 * region_rows)).cast("int").alias("parts"), F.min("angle").alias("low"), F.max("angle").alias("high"))
    sizes = saved(sizes, "region-sizes")
    data = placed.join(sizes.select(*key, "parts"), key).withColumn("part", F.pmod(F.xxhash64("rep"), "parts").cast("int"))
    shape = f"label {kind}, dim int, home int, part int, reps array<{id_kind}>, weights array<bigint>, units binary, starts array<int>, links array<int>, medoids array<int>, rep {id_kind}, n bigint, root {id_kind}"
    split = bool(centres) or bool(sizes.where("parts > 1").limit(1).count())

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        return _build(pdf, least, split)

    graphs = saved(data.select(*key, "part", "rep", "weight", "unit").groupBy(*key, "part").applyInPandas(build, shape), "graphs")
    met = graphs.where("rep is not null").select("rep", "n", "root")
    if split:
        met = met.unionByName(saved(_across(placed, sizes, graphs, centres, reach, query_rows, least, kind, id_kind), "vector-links"))
    per = met.where("n is not null").groupBy("rep").agg(F.sum("n").alias("n_links"))
    comp = connected_components(met.where("root is not null").select(F.col("rep").alias("a"), F.col("root").alias("b")))
    recall = _audit(placed, per, least, audit_rows)
    named = sound.select("vec_id", "label", "embedding").join(nodes.select("label", "embedding", "rep"), ["label", "embedding"]).select("vec_id", "rep")
    linked = named.join(per, "rep", "left").join(comp.withColumnRenamed("node", "rep"), "rep", "left").select(
        "vec_id", F.coalesce(F.col("n_links") - 1, F.lit(0)).alias("n_links"), F.coalesce("component", "rep").alias("component_id")
    )
    bad = base.where(~F.coalesce(_sound(), F.lit(False))).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.unionByName(bad).withColumn("kept", F.col("vec_id") == F.col("component_id")), recall


def _home(centres: np.ndarray | None, unit: np.ndarray) -> tuple[int, float]:
    """The nearest centre and the angle to it."""
    if centres is None:
        return 0, 0.0
    s = centres @ np.asarray(unit)
    i = int(np.argmax(s))
    return i, float(np.arccos(np.clip(s[i], -1.0, 1.0)))


def _across(placed: DataFrame, sizes: DataFrame, graphs: DataFrame, centres: dict, reach: float, query_rows: int, least: float, kind: str, id_kind: str) -> DataFrame:
    """Links between region parts: each node against every other part that may hold one of its links."""
    spark = placed.sparkSession
    bounds: dict[tuple, list] = {}
    for r in sizes.where("parts > 0").collect() if centres else []:  # regions, at most the sample's size a label
        bounds.setdefault((r.label, r.dim), []).append((r.home, r.low, r.high))
    held = spark.sparkContext.broadcast((centres, bounds))

    @F.pandas_udf("array<int>")
    def may_hold(label: pd.Series, dim: pd.Series, units: pd.Series) -> pd.Series:
        out = []
        for k, d, u in zip(label.tolist(), dim.tolist(), units):
            c = held.value[0].get((k, d))
            if c is None:
                out.append([0])
                continue
            angle = np.arccos(np.clip(c @ np.asarray(u), -1.0, 1.0))
            out.append([h for h, low, high in held.value[1][k, d] if low - reach <= angle[h] <= high + reach])
        return pd.Series(out)

    key = ["label", "dim", "home"]
    asked = placed.select("label", "dim", "rep", "unit", F.col("home").alias("own"), F.explode(may_hold("label", "dim", "unit")).alias("home")).join(sizes.select(*key, "parts"), key)
    asked = asked.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    asked = asked.where(~((F.col("own") == F.col("home")) & (F.col("part") == F.pmod(F.xxhash64("rep"), "parts"))))  # its own part has been searched
    asked = asked.select(*key, "part", "rep", "unit", F.pmod(F.xxhash64(F.lit(1), "rep"), F.lit(1 << 30)).alias("h"))
    totals = asked.groupBy(*key, "part").agg(F.ceil(F.count("*") / query_rows).cast("int").alias("blocks"))
    asked = asked.join(totals, [*key, "part"]).withColumn("block", F.pmod(F.col("h"), "blocks").cast("int")).drop("h", "blocks")
    holders = graphs.where("reps is not null").drop("rep", "n", "root").join(totals, [*key, "part"]).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")
    keys = [*key, "part", "block"]

    def search(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if left.empty or right.empty:
            return pd.DataFrame({"rep": [], "n": [], "root": []})
        g = left.iloc[0]
        starts, x = np.asarray(g["starts"]), np.frombuffer(g["units"], np.float64).reshape(-1, int(g["dim"]))
        links = [np.asarray(g["links"])[a:b] for a, b in zip(starts[:-1], starts[1:])]
        return _search(np.asarray(g["reps"]), np.asarray(g["weights"]), x, links, np.asarray(g["medoids"]), right["rep"].tolist(), np.stack(right["unit"].to_list()), None, least)

    return holders.groupBy(*keys).cogroup(asked.groupBy(*keys)).applyInPandas(search, f"rep {id_kind}, n bigint, root {id_kind}")


def _build(pdf: pd.DataFrame, least: float, store: bool) -> pd.DataFrame:
    """The graph of a region part as one row, if others are to search it, and what its own nodes find in it."""
    pdf = pdf.sort_values("rep")
    x = np.stack(pdf["unit"].to_list()).astype(np.float64)
    links, medoids = graph.build(x)
    starts = np.concatenate([[0], np.cumsum([len(k) for k in links])])
    reps, weights = pdf["rep"].to_numpy(), pdf["weight"].to_numpy()
    found = _search(reps, weights, x, links, medoids, reps.tolist(), x, range(len(reps)), least)
    head = {c: pdf[c].iloc[0] for c in ("label", "dim", "home", "part")}
    empty = {"reps": None, "weights": None, "units": None, "starts": None, "links": None, "medoids": None}
    rows = found.assign(**head, **empty)
    if store:
        one = head | {"reps": reps, "weights": weights, "units": x.tobytes(), "starts": starts.astype(np.int32), "links": np.concatenate(links) if starts[-1] else np.zeros(0, np.int32), "medoids": np.asarray(medoids, np.int32)}
        own = pd.DataFrame({k: [v] for k, v in one.items()} | {"rep": [None], "n": [None], "root": [None]})
        rows = pd.concat([rows, own]) if len(rows) else own
    return rows[["label", "dim", "home", "part", "reps", "weights", "units", "starts", "links", "medoids", "rep", "n", "root"]]


def _search(reps, weights, x, links, medoids, asked: list, units: np.ndarray, own, least: float) -> pd.DataFrame:
    """(rep, n, null) for each query: the weight of what it links with here, itself included if here; (node, null, root) for the spanning forest."""
    medoids = np.unique(np.asarray(medoids))
    parent: dict = {}

    def root(i):
        while parent.setdefault(i, i) != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    ids, counts = [], []
    for i, (rep, q) in enumerate(zip(asked, units)):
        at = own[i] if own is not None else None
        hits = graph.range_search(x, links, medoids, q, least, at)
        hits = hits[(x[hits] @ q >= least) | (reps[hits] == rep)]
        if not len(hits) and own is None:
            continue
        ids.append(rep)
        counts.append(int(weights[hits].sum()))
        if len(hits) < 2 and own is not None:
            continue
        a = root(rep)
        for b in {root(i) for i in reps[hits].tolist()}:
            if a != b:
                a, b = min(a, b), max(a, b)
                parent[b] = a
    tree = [(i, r) for i in list(parent) if (r := root(i)) != i]
    return pd.DataFrame({"rep": ids + [i for i, _ in tree], "n": pd.array(counts + [None] * len(tree), "Int64"), "root": pd.Series([None] * len(ids) + [r for _, r in tree], dtype=object)})


def _audit(placed: DataFrame, per: DataFrame, least: float, rows: int) -> float:
    """Links found over links there for at most ``rows`` nodes whose id is divisible by 20, each held against all nodes of its label."""
    spark = placed.sparkSession
    some = placed.where(F.pmod(F.xxhash64("rep") if dict(placed.dtypes)["rep"] == "string" else F.col("rep"), F.lit(20)) == 0)
    some = some.orderBy(F.xxhash64(F.lit(9), "rep"), "rep").limit(rows).select("label", "dim", "rep", "unit").collect() if rows else []
    if not some:
        return 1.0
    groups: dict[tuple, tuple] = {}
    for r in some:
        ids, units = groups.setdefault((r.label, r.dim), ([], []))
        ids.append(r.rep)
        units.append(r.unit)
    held = spark.sparkContext.broadcast({k: (ids, np.array(units)) for k, (ids, units) in groups.items()})  # ``rows`` vectors

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out: dict = {}
            for k, own in batch.groupby(["label", "dim"]):
                ids, units = held.value.get(k, ((), None))
                if not ids:
                    continue
                for at in range(0, len(own), 2048):
                    part = own.iloc[at : at + 2048]
                    hits = (units @ np.stack(part["unit"].to_list()).T >= least) | (np.array(ids)[:, None] == part["rep"].to_numpy()[None])
                    for i, n in zip(ids, (hits * part["weight"].to_numpy()).sum(1).tolist()):
                        out[i] = out.get(i, 0) + n
            yield pd.DataFrame({"rep": list(out), "n": list(out.values())})

    kind = placed.schema["rep"].dataType.simpleString()
    truth = placed.select("label", "dim", "rep", "weight", "unit").mapInPandas(compare, f"rep {kind}, n bigint").groupBy("rep").agg(F.sum("n").alias("truth"))
    row = truth.join(per, "rep", "left").agg(F.sum(F.col("truth") - 1).alias("t"), F.sum(F.least("truth", F.coalesce("n_links", F.lit(0))) - 1).alias("g")).first()
    return 1.0 if not row.t else row.g / row.t
