"""Chat formatting: calls and results are hash-joined by identifier, ordered by their dependencies, arguments are
validated against schemas, and every message is serialised as canonical JSON.

Every step works on single messages, so a conversation of any length is spread over tasks. Levels come from pointer doubling
along calls that wait for one other, so that a chain of n calls takes about log2(n) rounds, and from rounds over calls that
wait for several, in which only what was found last is joined. ``in_order`` writes conversations in topological order.
"""

from __future__ import annotations

import json
import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, keep, running_total

_TYPES = {"object": dict, "array": list, "string": str, "boolean": bool, "null": type(None)}


def canonical(value) -> str:
    """JSON without spaces, keys in code point order, non-ASCII as it is; whole floats as integers; no NaN or infinity."""

    def plain(v):
        if isinstance(v, dict):
            return {str(k): plain(x) for k, x in v.items()}
        if isinstance(v, list):
            return [plain(x) for x in v]
        if isinstance(v, float):
            if not math.isfinite(v):
                raise ValueError("not a JSON number")
            return int(v) if v.is_integer() and abs(v) < 1 << 53 else v
        return v

    return json.dumps(plain(value), ensure_ascii=False, sort_keys=True, separators=(",", ":"), allow_nan=False)


def problems(value, schema: dict, at: str = "$") -> list[str]:
    """What in a value is against a schema: type, enum, required, properties, additionalProperties, items, bounds of
    numbers and lengths."""
    out: list[str] = []
    kinds = schema.get("type")
    kinds = [kinds] if isinstance(kinds, str) else kinds
    if kinds:
        number = isinstance(value, int | float) and not isinstance(value, bool)
        whole = number and float(value).is_integer()
        if not any((k == "number" and number) or (k == "integer" and whole) or (k in _TYPES and isinstance(value, _TYPES[k]) and not (k != "boolean" and isinstance(value, bool))) for k in kinds):
            return [f"{at}: type"]
    if "enum" in schema and value not in schema["enum"]:
        out.append(f"{at}: enum")
    if isinstance(value, dict):
        known = schema.get("properties", {})
        out += [f"{at}.{k}: missing" for k in schema.get("required", []) if k not in value]
        for k, v in value.items():
            if k in known:
                out += problems(v, known[k], f"{at}.{k}")
            elif schema.get("additionalProperties", True) is False:
                out.append(f"{at}.{k}: unknown")
    if isinstance(value, list):
        for i, v in enumerate(value if "items" in schema else []):
            out += problems(v, schema["items"], f"{at}[{i}]")
    if isinstance(value, str) and not schema.get("minLength", 0) <= len(value) <= schema.get("maxLength", math.inf):
        out.append(f"{at}: length")
    if isinstance(value, int | float) and not isinstance(value, bool) and not schema.get("minimum", -math.inf) <= value <= schema.get("maximum", math.inf):
        out.append(f"{at}: range")
    return out


def levels(calls: DataFrame) -> DataFrame:
    """conv_id, call_id, level: 0 for calls that wait for none, else one more than the highest level they wait for; -1 on
    or behind a cycle. Identifiers that don't exist are waited for by none. calls: conv_id, call_id, after (ids)."""
    me = ["conv_id", "call_id"]
    ids = keep(calls.select(*me).distinct(), "calls")
    waits = calls.select(*me, F.explode("after").alias("on")).distinct()
    waits = keep(waits.join(ids.withColumnRenamed("call_id", "on"), ["conv_id", "on"]).select(*me, "on"), "waits")
    needs = keep(waits.groupBy(*me).agg(F.count("*").alias("need"), F.min("on").alias("to")), "needs")
    # a call that waits for one other points at it; pointers are doubled until they end at a call that waits for none or several
    one = needs.where("need = 1").select(*me, "to", F.lit(1).cast("long").alias("far"))
    moving, still = keep(one, "pointers"), None
    rounds = max(moving.count(), 1).bit_length() + 1
    for _ in range(rounds):  # longer than any chain: what still moves lies on or behind a cycle
        ends = moving.select("conv_id", F.col("call_id").alias("to"), F.col("to").alias("_to"), F.col("far").alias("_far"))
        if still is not None:
            ends = ends.unionByName(still.select("conv_id", F.col("call_id").alias("to"), F.col("to").alias("_to"), F.col("far").alias("_far")))
        both = keep(moving.join(ends, ["conv_id", "to"], "left"), "pointers")
        done = both.where("_to is null").select(*me, "to", "far")
        still = keep(done if still is None else still.unionByName(done), "pointers")
        discard(moving)
        moving = keep(both.where("_to is not null").select(*me, F.col("_to").alias("to"), (F.col("far") + F.col("_far")).alias("far")), "pointers")
        discard(both)
        if moving.isEmpty():
            break
    # rounds over the calls that wait for several, each as soon as the ends of all its pointers have their level
    known = keep(ids.join(needs.select(*me), me, "left_anti").withColumn("level", F.lit(0).cast("long")), "levels")
    several = waits.join(needs.where("need > 1").select(*me, "need"), me)
    heads = still.select("conv_id", F.col("call_id").alias("on"), F.col("to").alias("head"), "far")
    open_ = keep(several.join(heads, ["conv_id", "on"], "left").select(*me, "need", F.coalesce("head", "on").alias("head"), (F.coalesce("far", F.lit(0)) + 1).alias("far")), "waiting")
    held = keep(open_.select(*me, "need").distinct().select(*me, "need", F.lit(0).cast("long").alias("got"), F.lit(0).cast("long").alias("level")), "held")
    new = known
    while not new.isEmpty() and not held.isEmpty():
        met = open_.join(new.select("conv_id", F.col("call_id").alias("head"), F.col("level").alias("at")), ["conv_id", "head"])
        sums = met.groupBy(*me).agg(F.count("*").alias("n"), F.max(F.col("at") + F.col("far")).alias("most"))
        now = held.join(sums, me, "left").select(*me, "need", (F.col("got") + F.coalesce("n", F.lit(0))).alias("got"), F.greatest("level", F.coalesce("most", F.lit(0))).alias("level"))
        now = keep(now, "held")
        new = keep(now.where("got = need").select(*me, "level"), "levels")
        known = known.unionByName(new)
        discard(held)
        held = keep(now.where("got < need"), "held")
        discard(now)
    ends = known.select("conv_id", F.col("call_id").alias("to"), "level")
    along = still.join(ends, ["conv_id", "to"]).select(*me, (F.col("level") + F.col("far")).alias("level"))
    return ids.join(known.unionByName(along), me, "left").withColumn("level", F.coalesce("level", F.lit(-1)).cast("int"))


def in_order(linked: DataFrame) -> DataFrame:
    """The rows of ``link`` with line: their place, from 0, when conversations follow one another (null last) and each has its
    messages by level, then turn: a call comes after the calls it waits for, a result after its call. The rows lie sorted so in
    files, however long a conversation is."""
    given = linked.withColumn("_one", F.lit(1).cast("long")).withColumn("_kind", F.when(F.col("kind") == "result", 1).otherwise(0))
    keys = [F.col("conv_id").asc_nulls_last(), "level", F.col("turn").asc_nulls_last(), "_kind", "json"]
    return running_total(given, keys, "_one", "line", "chat").drop("_one", "_kind")


def link(messages: DataFrame, schemas: dict[str, dict]) -> DataFrame:
    """One row for each message: conv_id, turn, kind, call_id, linked, valid, errors, level, json.

    messages: conv_id, turn, kind (call, result or text), call_id, name, arguments (JSON text), content, after (ids that
    the call waits for). A call is linked if a result with its identifier is in the conversation, a result if such a call
    is; each has its call's level. valid: a call's arguments are JSON and fit the schema of its name (a name without
    schema is invalid); a result is linked; other messages are valid. Nulls are written as null; a null identifier links
    with nothing. Repeated rows are kept.
    """
    calls = messages.where("kind = 'call' and call_id is not null and conv_id is not null").select("conv_id", "call_id", F.coalesce("after", F.array().cast("array<string>")).alias("after"))
    level = levels(calls)
    results = messages.where("kind = 'result' and call_id is not null and conv_id is not null").select("conv_id", "call_id").distinct().withColumn("_answered", F.lit(True))
    both = messages.join(level, ["conv_id", "call_id"], "left").join(results, ["conv_id", "call_id"], "left")
    linked = F.when(F.col("kind") == "call", F.coalesce("_answered", F.lit(False))).when(F.col("kind") == "result", F.col("level").isNotNull()).otherwise(False)
    sent = messages.sparkSession.sparkContext.broadcast(schemas)  # a stated table of functions

    @F.pandas_udf("errors array<string>, json string")
    def written(conv: pd.Series, turn: pd.Series, kind: pd.Series, call: pd.Series, name: pd.Series, arguments: pd.Series, content: pd.Series, role: pd.Series) -> pd.DataFrame:
        errors, lines = [], []

        def whole(v):
            return None if v is None or v != v else int(v)

        def given(v):
            return None if v is None or v != v else v

        for c, t, k, i, f, a, x, r in zip(conv, turn, kind, call, name, arguments, content, role, strict=True):
            row, found = {"content": given(x), "conversation": whole(c), "role": given(r), "turn": whole(t)}, []
            if k == "call":
                value = None
                try:
                    value = json.loads(a)
                    row["arguments"] = json.loads(canonical(value))
                except (TypeError, ValueError):
                    found.append("$: not JSON")
                    row["arguments"] = given(a)
                if not found:
                    found = problems(value, sent.value[f]) if f in sent.value else ["no schema"]
                row["name"] = given(f)
                del row["content"]
            if k in ("call", "result"):
                row["call_id"] = given(i)
            errors.append(found)
            lines.append(canonical(row))
        return pd.DataFrame({"errors": errors, "json": lines})

    out = both.withColumn("linked", linked).withColumn("_w", written("conv_id", "turn", "kind", "call_id", "name", "arguments", "content", "role"))
    valid = F.when(F.col("kind") == "call", F.size("_w.errors") == 0).when(F.col("kind") == "result", F.col("linked")).otherwise(True)
    return out.select("conv_id", "turn", "kind", "call_id", "linked", valid.alias("valid"), F.col("_w.errors").alias("errors"), F.coalesce("level", F.lit(0)).alias("level"), F.col("_w.json").alias("json"))
