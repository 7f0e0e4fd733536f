"""Training data without labels for one schema: windows over token blocks, judged by cosine."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dnfblock.operators.matcher import record_tokens


def generate_training(df: DataFrame, fields: list[str], c: int = 10, ut: float = 0.6, lt: float = 0.1, d: int = 100, nd: int = 100) -> DataFrame:
    """``label, l_rid, r_rid, score``: up to ``d`` duplicates above ``ut``, ``nd`` others below ``lt``.

    Records of a token's block stand in order of a hash; those at most ``c`` apart are compared, so
    work is linear in the index however frequent a token is.
    """
    tf = record_tokens(df, fields).groupBy("rid", "token").agg(F.count("*").alias("tf"))
    n = df.count()
    freq = tf.groupBy("token").agg(F.count("*").alias("df"))
    w = tf.join(freq, "token").withColumn("w", F.log1p("tf") * F.ln(F.lit(float(n)) / F.col("df")))
    norms = w.groupBy("rid").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    w = w.join(norms, "rid").where("norm > 0").select("rid", "token", (F.col("w") / F.col("norm")).alias("w"))
    order = Window.partitionBy("token").orderBy(F.md5(F.concat("token", "rid")), "rid")
    near = F.collect_list("rid").over(order.rowsBetween(1, c))
    pairs = w.withColumn("near", near).select("rid", F.explode("near").alias("other"))
    pairs = pairs.select(F.least("rid", "other").alias("l_rid"), F.greatest("rid", "other").alias("r_rid")).distinct()
    l = w.select(F.col("rid").alias("l_rid"), "token", F.col("w").alias("lw"))  # noqa: E741
    r = w.select(F.col("rid").alias("r_rid"), "token", F.col("w").alias("rw"))
    scored = pairs.join(l, "l_rid").join(r, ["r_rid", "token"]).groupBy("l_rid", "r_rid").agg(F.round(F.sum(F.col("lw") * F.col("rw")), 9).alias("score"))
    top = scored.where(F.col("score") > ut).orderBy(F.desc("score"), "l_rid", "r_rid").limit(d).withColumn("label", F.lit(1))
    low = scored.where(F.col("score") < lt).orderBy("score", "l_rid", "r_rid").limit(nd).withColumn("label", F.lit(0))
    return top.unionByName(low).select("label", "l_rid", "r_rid", "score")
