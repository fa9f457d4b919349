"""Architecture, utilisation, wall clock and cost arithmetic, and telemetry: throughput, slow steps, faults, determinism."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Architecture:
    """The published configuration of the base model."""

    layers: int = 18
    width: int = 2048
    heads: int = 16
    kv_heads: int = 8
    head_dim: int = 128
    ffn: int = 6144
    vocabulary: int = 65_536
    context: int = 4096
    tied: bool = True


@dataclass(frozen=True)
class Run:
    """The published run, and the dense bf16 peak of its accelerator."""

    tokens: float = 150e9
    batch_tokens: int = 2_097_152
    tokens_per_s: float = 68_052.0
    gpus: int = 8
    peak_flops: float = 989e12
    cost: str = "2500.00"
    budget: str = "2000.00"
    hours: float = 79.0
    optimal_ratio: float = 20.0
    first_mfu: float = 0.031


def arch_frame(spark: SparkSession, arch: Architecture = Architecture()) -> DataFrame:
    return spark.createDataFrame([(arch.layers, arch.width, arch.heads, arch.kv_heads, arch.head_dim, arch.ffn, arch.vocabulary, arch.context, arch.tied)], "layers long, width long, heads long, kv_heads long, head_dim long, ffn long, vocabulary long, context long, tied boolean")


def param_table(arch: DataFrame) -> DataFrame:
    """``component`` and ``params``, with a total: embeddings, attention with grouped keys, gated FFN, norms with those of queries and keys."""
    parts = arch.select(F.expr("""stack(5,
        'embedding', vocabulary * width * if(tied, 1, 2),
        'attention_qo', layers * 2 * width * heads * head_dim,
        'attention_kv', layers * 2 * width * kv_heads * head_dim,
        'ffn', layers * 3 * width * ffn,
        'norms', layers * (2 * width + 2 * head_dim) + width) as (component, params)"""))
    return parts.rollup("component").agg(F.sum("params").alias("params")).withColumn("component", F.coalesce("component", F.lit("total")))


def n_params(arch: Architecture = Architecture()) -> int:
    a = arch
    per_layer = 2 * a.width * a.head_dim * (a.heads + a.kv_heads) + 3 * a.width * a.ffn + 2 * a.width + 2 * a.head_dim
    return a.vocabulary * a.width * (1 if a.tied else 2) + a.layers * per_layer + a.width


def kv_bytes(arch: DataFrame, seq: int, dtype_bytes: int = 2) -> DataFrame:
    """Bytes of the key-value cache of one sequence, with and without grouped heads."""
    size = lambda heads: F.col("layers") * 2 * F.col(heads) * F.col("head_dim") * seq * dtype_bytes
    return arch.select(F.lit(seq).cast("long").alias("seq"), size("kv_heads").alias("grouped"), size("heads").alias("full"))


def train_flops(arch: Architecture = Architecture(), tokens: float = 1.0, include_attention: bool = False) -> float:
    attention = 12.0 * arch.layers * arch.width * arch.context if include_attention else 0.0
    return (6.0 * n_params(arch) + attention) * tokens


def mfu(run: Run = Run(), arch: Architecture = Architecture(), include_attention: bool = False) -> float:
    """Share of one accelerator's peak; the printed rate fits the printed share only for each accelerator."""
    return train_flops(arch, run.tokens_per_s, include_attention) / run.peak_flops


def run_plan(spark: SparkSession, run: Run = Run(), arch: Architecture = Architecture()) -> DataFrame:
    one = spark.createDataFrame([(run.tokens, float(run.batch_tokens), run.tokens_per_s, float(run.gpus), float(arch.context))], "tokens double, batch double, rate double, gpus double, context double")
    return one.select(
        F.round(F.col("tokens") / F.col("batch"), 1).alias("steps"),
        (F.col("batch") / F.col("context")).alias("sequences_per_step"),
        F.round(F.col("tokens") / (F.col("rate") * F.col("gpus")) / 3600, 2).alias("hours_per_gpu_rate"),
        F.round(F.col("tokens") / F.col("rate") / 3600, 2).alias("hours_per_node_rate"),
    )


def costs(runs: DataFrame, gpus: float) -> DataFrame:
    """``runs`` with the unit costs of their ``cost``, ``budget``, ``hours`` and ``billions`` of tokens; null where a measure is 0."""
    d = F.col("cost").cast("double")
    over = lambda x: d / F.nullif(x, F.lit(0.0))
    return runs.withColumns({
        "per_node_hour": F.round(over(F.col("hours")), 2),
        "per_gpu_hour": F.round(over(F.col("hours")) / gpus, 2),
        "per_billion_tokens": F.round(over(F.col("billions")), 2),
        "of_budget": F.round(over(F.col("budget").cast("double")), 4),
    })


def _priced(runs: DataFrame, run: Run) -> DataFrame:
    return runs.withColumns({"cost": F.lit(run.cost).cast("decimal(12,2)"), "budget": F.lit(run.budget).cast("decimal(12,2)")})


def cost_report(spark: SparkSession, run: Run = Run()) -> DataFrame:
    one = spark.range(1).select(F.lit(run.hours).alias("hours"), F.lit(run.tokens / 1e9).alias("billions"))
    return costs(_priced(one, run), run.gpus).select("cost", "budget", "per_node_hour", "per_gpu_hour", "per_billion_tokens", "of_budget")


def telemetry_costs(events: DataFrame, run: Run = Run(), by: str = "user_id") -> DataFrame:
    """Unit costs of one run for each ``by``, all at the published bill: hours from its first event to its last, billions of tokens from its values."""
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    hours = (F.max(micros) - F.min(micros)).cast("double") / 3.6e9
    spent = events.groupBy(by).agg(hours.alias("hours"), F.sum(F.col("value").cast("decimal(18,4)")).cast("double").alias("billions"))
    return costs(_priced(spent, run), run.gpus).select(by, "per_node_hour", "per_gpu_hour", "per_billion_tokens", "of_budget")


def overtraining(run: Run = Run(), arch: Architecture = Architecture()) -> tuple[float, float]:
    """Tokens for each parameter, and times the compute-optimal ratio."""
    ratio = run.tokens / n_params(arch)
    return ratio, ratio / run.optimal_ratio


def throughput(events: DataFrame, window: str = "1 hour") -> DataFrame:
    """Rows and units of measurement by time window."""
    measured = events.where("event_type = 'value' or value is not null")
    by = measured.groupBy(F.window("ts", window).alias("w"))
    return by.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("units")).select(F.col("w.start").alias("start"), "n", "units")


def slow_steps(steps: DataFrame, k: int = 10, ratio: float = 0.5, *, order: list[str], by: list[str], rate: str = "value", centre: str = "mean") -> DataFrame:
    """Steps whose rate is below ``ratio`` of the mean (or lower median) of the ``k`` before: a silent fall-back to a slow path."""
    before = Window.partitionBy(*by).orderBy(*order).rowsBetween(-k, -1)
    middle = F.percentile_approx(rate, 0.5, 1_000_000) if centre == "median" else F.avg(rate)
    trailing = steps.withColumn("trailing", middle.over(before)).withColumn("_n", F.count(rate).over(before))
    return trailing.where((F.col("_n") == k) & (F.col(rate) < ratio * F.col("trailing"))).drop("_n")


def determinism_audit(one: DataFrame, two: DataFrame, keys: list[str]) -> DataFrame:
    """Keys whose rows differ between two runs, or that one run lacks; compared by digests of all other columns."""

    def digest(df: DataFrame, name: str) -> DataFrame:
        rest = [c for c in sorted(df.columns) if c not in keys]
        return df.select(*keys, F.md5(F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("\0")) for c in rest])).alias(name))

    both = digest(one, "first").join(digest(two, "second"), keys, "full")
    state = F.when(F.col("first").isNull(), "missing_first").when(F.col("second").isNull(), "missing_second").otherwise("differs")
    return both.where(~F.col("first").eqNullSafe(F.col("second"))).select(*keys, state.alias("state"))


def fault_sessions(events: DataFrame, gap: str = "30 minutes", *, kind: str = "error", by: str = "user_id") -> DataFrame:
    """Runs of faults of one device with pauses below ``gap``: begin, end, faults."""
    seconds = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    w = Window.partitionBy(by).orderBy("ts", "event_id")
    faults = events.where(F.col("event_type") == kind).withColumn("_s", seconds)
    limit = _seconds(gap)
    new = F.coalesce((F.col("_s") - F.lag("_s").over(w) >= limit).cast("int"), F.lit(1))
    runs = faults.withColumn("_new", new).withColumn("_run", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return runs.groupBy(by, "_run").agg(F.min("ts").alias("begin"), F.max("ts").alias("end"), F.count(F.lit(1)).alias("faults")).drop("_run")


def _seconds(text: str) -> int:
    n, unit = text.split()
    return int(n) * {"second": 1, "minute": 60, "hour": 3600, "day": 86_400}[unit.rstrip("s")]


def speedup(before: Column, after: Column) -> Column:
    return F.round(after / before, 2)
