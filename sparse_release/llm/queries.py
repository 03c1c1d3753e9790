"""The operators' queries, each over its whole table, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import license_scan, near_dup, oracle, packing, quality_rules, secret_scan, source_mixing, substring_dedup, topk_search, toxicity, url_rules
from .common import documents

Query = Callable[[SparkSession, str], DataFrame]


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = substring_dedup.dedup_substrings(documents(spark, sf_dir))
    lost = F.aggregate("removed", F.lit(0).cast("long"), lambda a, r: a + r["end"] - r["start"])
    return done.select("doc_id", "n_words", lost.alias("n_removed"), F.sha2("kept_text", 256).alias("kept_sha256"))


def op2_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("id"), "embedding")
    fine = rows.where("embedding IS NOT NULL AND forall(embedding, x -> x IS NOT NULL AND NOT isnan(x) AND abs(x) < double('Infinity'))")
    whole = fine.selectExpr("id", "transform(embedding, x -> CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS vec")
    found = topk_search.top_k(whole, whole.where("id % 50 = 0"), 5)
    return found.select("query_id", "rank", F.col("id").alias("vec_id"), "score")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, col = quality_rules.ledger(documents(spark, sf_dir).select("doc_id", "text"))
    led = F.col(col)
    base = ~quality_rules.passes(led["failures"], "base")
    return rows.select("doc_id", led["n_words"].alias("n_words"), *[led[k].alias(k) for k in ("word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], base.alias("base_failed"), quality_rules.passes(led["failures"], "v1").alias("kept"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    remainder = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5
    scored = toxicity.score(docs, toxicity.fit(docs, labels.where(remainder != 0)))
    return scored.select("doc_id", F.coalesce(remainder == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


#: The list of rules that op5's contract states.
URL_RULES = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))


def op5_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(list(URL_RULES), "host string, path string, verdict string")
    return url_rules.match_rules(spark.read.parquet(f"{sf_dir}/pages.parquet"), rules)


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = license_scan.scan_licenses(documents(spark, sf_dir))
    return found.select("doc_id", "digest", "license", F.array_join("notices", ",").alias("notices"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, col = secret_scan.secret_spans(documents(spark, sf_dir).select("doc_id", "text"))
    base = f"`{col}`.base"
    counts = [f"CAST(size(filter({base}, v -> v.k = {k})) AS BIGINT) AS n_{kind}" for k, (kind, _, _) in enumerate(secret_scan.KINDS[: secret_scan.N_BASE])]
    return rows.selectExpr("doc_id", *counts, f"sha2({secret_scan.spelled(base)}, 256) AS base_sha256", f"{secret_scan.spelled(f'`{col}`.spans')} AS spans")


def op8_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(documents(spark, sf_dir)).select("doc_id", near_dup.spelled().alias("fingerprint"), "component_id")


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.pack_documents(documents(spark, sf_dir), vocabulary())
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "tier", "step")


def op10_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mix = source_mixing.mix_sources(documents(spark, sf_dir))
    each = mix.withColumn("one", F.explode(F.sequence(F.lit(1).cast("long"), F.col("repeats"))))
    return each.select(F.col("id").alias("doc_id"), "size", "source_size", "target", ((F.col("base") + (F.col("one") <= F.col("extra")).cast("long")) * F.col("size")).alias("taken"))


QUERIES: dict[str, Query] = {
    "op1_substring_dedup": op1_substring_dedup,
    "op2_topk_search": op2_topk_search,
    "op3_quality_rules": op3_quality_rules,
    "op4_toxicity": op4_toxicity,
    "op5_url_rules": op5_url_rules,
    "op6_license_scan": op6_license_scan,
    "op7_secret_scan": op7_secret_scan,
    "op8_near_dup": op8_near_dup,
    "op9_packing": op9_packing,
    "op10_source_mixing": op10_source_mixing,
}
#: The rest is beyond SQL on whole tables (fitted models, fingerprints by component, packing, dependent rounding, linked parts); tests compare it with plain versions.
ORACLE_SQL: dict[str, str] = {
    "op1_substring_dedup": oracle.substring_dedup(),
    "op2_topk_search": oracle.topk_search(),
    "op3_quality_rules": oracle.quality_rules(),
    "op5_url_rules": oracle.url_rules(URL_RULES),
    "op6_license_scan": oracle.license_scan(),
}
