"""Exclusive feature bundling: features that are (almost) never non-zero together share a column."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def feature_counts(feats: DataFrame) -> DataFrame:
    """(f, n) from long rows (rid, f, v)."""
    return feats.filter("v != 0").groupBy("f").agg(F.count(F.lit(1)).alias("n"))


def conflicts(feats: DataFrame) -> DataFrame:
    """(f1, f2, n), f1 < f2: rows in which both are non-zero; only pairs that occur."""
    some = feats.filter("v != 0").select("rid", "f").distinct()
    other = some.withColumnRenamed("f", "f2")
    return some.withColumnRenamed("f", "f1").join(other, "rid").filter("f1 < f2").groupBy("f1", "f2").agg(F.count(F.lit(1)).alias("n"))


def bundle_features(feats: DataFrame, max_conflict: int = 0, most_features: int = 100_000) -> dict[str, tuple[int, int]]:
    """feature -> (bundle, offset). Features by falling count go to the first bundle whose conflicts stay allowed.

    The greedy colouring runs on the driver over the features, at most `most_features` of them; wider data
    comes as known one-hot groups (see one_hot_bundles), which need no counting.
    """
    counts = feature_counts(feats).orderBy(F.col("n").desc(), "f").limit(most_features + 1).collect()
    if len(counts) > most_features:
        raise ValueError("too many features to colour on the driver; give one-hot groups")
    clash: dict[str, dict[str, int]] = {}
    for r in conflicts(feats).collect():
        clash.setdefault(r["f1"], {})[r["f2"]] = r["n"]
        clash.setdefault(r["f2"], {})[r["f1"]] = r["n"]
    bundles: list[list[str]] = []
    spent: list[int] = []
    out: dict[str, tuple[int, int]] = {}
    for r in counts:
        own = clash.get(r["f"], {})
        for k, members in enumerate(bundles):
            cost = sum(own.get(m, 0) for m in members)
            if spent[k] + cost <= max_conflict:
                members.append(r["f"])
                spent[k] += cost
                out[r["f"]] = (k, len(members))
                break
        else:
            bundles.append([r["f"]])
            spent.append(0)
            out[r["f"]] = (len(bundles) - 1, 1)
    return out


def one_hot_bundles(features: list[str]) -> dict[str, tuple[int, int]]:
    """Bundles of one-hot names `column=value`: one for each column, without any conflict."""
    names = sorted({f.split("=", 1)[0] for f in features})
    seen: dict[str, int] = {}
    out = {}
    for f in sorted(features):
        name = f.split("=", 1)[0]
        seen[name] = seen.get(name, 0) + 1
        out[f] = (names.index(name), seen[name])
    return out


def bundled_vector(df: DataFrame, bundles: dict[str, tuple[int, int]]) -> DataFrame:
    """(rid, y, x): x holds each bundle's offset of the feature present, 0 where none is, from sparse feats."""
    width = max((b for b, _ in bundles.values()), default=-1) + 1
    spark = df.sparkSession
    table = F.broadcast(spark.createDataFrame([(f, b, o) for f, (b, o) in bundles.items()], "f string, bundle int, offset int"))
    long = df.select("rid", F.explode("feats").alias("x")).select("rid", "x.f").join(table, "f")
    packed = long.groupBy("rid").agg(F.map_from_entries(F.collect_list(F.struct("bundle", F.col("offset").cast("double")))).alias("m"))
    value = lambda k: F.coalesce(F.element_at("m", F.lit(k)), F.lit(0.0))
    return df.select("rid", "y").join(packed, "rid", "left").select("rid", "y", F.array(*[value(k) for k in range(width)]).alias("x"))
