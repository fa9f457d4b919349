"""Instruction sets: turns, conditions, manifests, rendering, loss masks, and the three iterations of the set."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.views import bucket

#: The tool catalogue: name, category, signature (names of our own).
CATALOG = (
    ("add_numbers", "arithmetic", "expression:string"),
    ("change_units", "units", "amount:double,from:string,to:string"),
    ("read_weather", "weather", "place:string"),
    ("swap_currency", "currency", "amount:double,from:string,to:string"),
    ("open_calendar", "calendar", "day:string"),
    ("look_up_word", "dictionary", "word:string"),
    ("draw_map", "map", "place:string"),
    ("list_news", "news", "topic:string"),
    ("set_timer", "timer", "minutes:int"),
    ("translate_text", "translator", "text:string,to:string"),
)
TASKS = ("arithmetic", "units", "weather", "currency", "free_form")
TOOL_OF = {c: n for n, c, _ in CATALOG}
DECLINE = {
    "en": "None of the tools at hand fits this; tell me the figures and I will go through them here.",
    "de": "Keines der Werkzeuge passt dazu; nenne mir die Angaben, dann gehe ich sie hier durch.",
    "fr": "Aucun outil ne convient ; donnez-moi les chiffres et je les reprends ici.",
    "es": "Ninguna herramienta sirve para esto; dame los datos y los repaso aquí.",
}


def catalog_frame(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(CATALOG, "name string, category string, signature string")


def _catalog_array() -> Column:
    return F.array(*[F.struct(F.lit(n).alias("name"), F.lit(c).alias("category"), F.lit(s).alias("signature")) for n, c, s in CATALOG])


def assemble(conv: DataFrame) -> DataFrame:
    """Turns of each conversation in order, as one array; one shuffle by conversation."""
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", "text")))
    return conv.groupBy("conv_id").agg(turns.alias("turns"), F.count(F.lit(1)).alias("n_turns"))


def validate_turns(conv: DataFrame) -> DataFrame:
    """Per conversation: do roles alternate, is a system turn first if any, does the user end it."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    told = conv.withColumns({"before": F.lag("role").over(w), "last": F.lead("role").over(w).isNull()})
    bad = (F.col("role") == F.col("before")) | ((F.col("role") == "system") & F.col("before").isNotNull())
    return told.groupBy("conv_id").agg(
        (~F.bool_or(F.coalesce(bad, F.lit(False)))).alias("alternates"),
        F.bool_or(F.col("last") & (F.col("role") == "user")).alias("ends_with_user"),
        F.bool_or(F.col("role") == "system").alias("has_system"),
    )


def condition_of(has_manifest: Column, needs_tool: Column, fits: Column) -> Column:
    """A call; B decline, none fits; C not needed; D no manifest."""
    return F.when(~has_manifest, "D").when(~needs_tool, "C").when(fits, "A").otherwise("B")


def tag_turns(conv: DataFrame) -> DataFrame:
    """Every user turn with its task, condition and the tool that the task calls for, by md5 arithmetic alone."""
    key = (F.col("conv_id"), F.col("turn"))
    h, t = bucket("cond", *key), bucket("task", *key) % 5
    share = h % 10
    task = F.element_at(F.array(*map(F.lit, TASKS)), (t + 1).cast("int"))
    drawn = F.when(share <= 3, "A").when(share <= 5, "B").when(share <= 7, "C").otherwise("D")
    condition = F.when((task == "free_form") & drawn.isin("A", "B"), "C").otherwise(drawn)
    tools = F.create_map(*[F.lit(x) for kv in TOOL_OF.items() for x in kv])
    tagged = conv.where("role = 'user'").select("conv_id", "turn", "text", task.alias("task"), condition.alias("condition"), F.pmod(F.shiftright(h, 4), F.lit(6)).alias("_k"))
    return tagged.withColumns({"tool": F.when(F.col("condition") == "A", F.element_at(tools, F.col("task"))), "distractors": (F.col("_k") + 2).cast("int")}).drop("_k")


def synthesize_manifest(tagged: DataFrame) -> DataFrame:
    """``tagged`` with ``manifest``: the called tool and 2 to 7 distractors in an order that gives no cue; B has distractors only; D none.

    Row-local: no shuffle and no join with the catalogue.
    """
    key = [F.col("conv_id").cast("string"), F.col("turn").cast("string")]
    rank = lambda tag: lambda x: F.struct(F.md5(F.concat_ws("|", F.lit(tag), *key, x["name"])).alias("h"), x.alias("tool"))
    others = F.filter(_catalog_array(), lambda x: x["category"] != F.col("task"))
    drawn = F.transform(F.slice(F.array_sort(F.transform(others, rank("dist"))), F.lit(1), F.col("distractors")), lambda x: x["tool"])
    called = F.filter(_catalog_array(), lambda x: (F.col("condition") == "A") & (x["name"] == F.col("tool")))
    whole = F.transform(F.array_sort(F.transform(F.concat(drawn, called), rank("ord"))), lambda x: x["tool"])
    return tagged.withColumn("manifest", F.when(F.col("condition") != "D", whole))


def decline_turn(lang: Column) -> Column:
    table = F.create_map(*[F.lit(x) for kv in DECLINE.items() for x in kv])
    return F.coalesce(F.element_at(table, lang), F.lit(DECLINE["en"]))


def _segment(kind: str, text: Column, trainable: bool) -> Column:
    return F.struct(F.lit(kind).alias("kind"), text.alias("text"), F.lit(trainable).alias("trainable"))


def segments(manifests: DataFrame, answers: DataFrame, lang: Column | None = None) -> DataFrame:
    """``conv_id``, ``turn`` and ``segments``: manifest and user masked, the assistant's part trained. Turns without an answer are left out, but for B's, whose answer is the declining turn of ``lang``."""
    told = manifests.join(answers, ["conv_id", "turn"], "left")
    call = F.concat(F.lit("<call>"), F.col("tool"))
    answer = F.when(F.col("condition") == "A", call).when(F.col("condition") == "B", decline_turn(F.lit("en") if lang is None else lang)).otherwise(F.col("answer"))
    parts = F.array(
        F.when(F.col("manifest").isNotNull(), _segment("manifest", F.to_json("manifest"), False)),
        _segment("user", F.col("text"), False),
        _segment("assistant", answer, True),
    )
    return told.where(answer.isNotNull()).select("conv_id", "turn", "condition", "task", F.filter(parts, lambda s: s.isNotNull()).alias("segments"))


def answers_of(conv: DataFrame) -> DataFrame:
    """The assistant's text after each user turn."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    after = conv.withColumns({"answer": F.lead("text").over(w), "_r": F.lead("role").over(w)})
    return after.where("role = 'user' and _r = 'assistant'").select("conv_id", "turn", "answer")


def render_chat(parts: Column) -> Column:
    """A transcript with role markers."""
    return F.array_join(F.transform(parts, lambda s: F.concat(F.lit("<|"), s["kind"], F.lit("|>"), s["text"])), "\n")


def masked_share(sft: DataFrame, by: list[str]) -> DataFrame:
    """Characters that are trained and masked."""
    length = lambda keep: F.aggregate(F.filter("segments", lambda s: s["trainable"] == keep), F.lit(0), lambda a, s: a + F.length(s["text"]))
    return sft.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum(length(True)).cast("long").alias("trained_chars"), F.sum(length(False)).cast("long").alias("masked_chars"))


def manifest_leaks(sft: DataFrame) -> DataFrame:
    """Examples whose trained text holds manifest text; none is expected."""
    of = lambda kind: F.filter("segments", lambda s: s["kind"] == kind)
    leaks = F.exists(of("manifest"), lambda m: F.exists("segments", lambda s: s["trainable"] & F.contains(s["text"], m["text"])))
    return sft.where(leaks)


def turn_lang(conv_id: Column) -> Column:
    """The fixture language of a conversation: the languages of the declining turns, in turn."""
    return F.element_at(F.array(*map(F.lit, DECLINE)), (F.pmod(conv_id, F.lit(len(DECLINE))) + 1).cast("int"))


def mixture_report(sft: DataFrame, axes: tuple[str, ...] = ("task", "condition")) -> DataFrame:
    """Volume by task and condition (and any further axis) with all totals, which shows thin categories."""
    return sft.cube(*axes).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level"))


def build_set(conv: DataFrame, version: str, *, safety: DataFrame | None = None, share: float = 0.1) -> DataFrame:
    """``v1``: no system turns. ``v2``: v1 and safety examples (``conv_id, turn, role, text``) to a share of all. ``v3``: manifest-conditioned segments."""
    if version == "v3":
        return segments(synthesize_manifest(tag_turns(conv)), answers_of(conv))
    plain = conv.where("role <> 'system'").withColumn("origin", F.lit("general"))
    if version == "v1":
        return plain
    n = plain.count()
    more = safety.orderBy(bucket("safety", F.col("conv_id"), F.col("turn")), "conv_id", "turn").limit(int(n * share / (1 - share))).withColumn("origin", F.lit("safety"))
    return plain.unionByName(more)
