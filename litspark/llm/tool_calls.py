"""Tool-call linking: calls meet results by identifier, stand in topological order, are validated and serialised.

``link_tool_calls(calls, results, schemas)``:

1. Hash join of calls and results on (conv_id, call_id).  The first call of an
   identifier and its first result count; the others are reported as repeated.
2. Topological levels from the calls' ``parents`` (identifiers whose results a
   call uses): 0 without known parents, else one more than the highest parent;
   none on a cycle or behind one.  Calls are numbered in the order (conv_id, turn,
   call_id) of a range-partitioned sort and cut into blocks of at most ``BLOCK``
   calls of one conversation.  A block is solved by one expression: a fold in that
   order, then sweeps for calls whose parents come later.  Levels travel between
   blocks in rounds, so a conversation of up to ``BLOCK`` calls takes one round or
   two, however deep it is, and a longer one a round for each block that a chain
   passes through.
   Position is the dense order of (level, turn, call_id) in the conversation, read
   off a second sort and the counts of its partitions.
3. Arguments are validated against the schema of their tool: a JSON object,
   every required field present, every present field of its type, no unknown
   field where the schema is closed.
4. Each linked call becomes canonical JSON: keys sorted, no blanks.

Everything is DataFrame expressions.  Keys are (conv_id, call_id), blocks or
partitions of a sort, so that a conversation with a third of all calls is spread
over tasks; only counts of partitions are grouped by conversation.

Edge cases: calls with a null conv_id or call_id link with nothing; results
without a call are returned as orphans; null or malformed arguments are invalid;
an unknown tool is invalid; ties in turn go by call_id; empty tables give an empty
result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from litspark.llm.common import Scratch, small
from litspark.llm.quality_rules import let

#: Calls of one block, which one expression solves; a power of two, so that no block crosses a partition of the numbering.
BLOCK = 4096
#: Tables of finished blocks that are read side by side before they are written as one.
PARTS = 8

# Kinds of fields and the names of their shapes.
KINDS = {"string": "STRING", "integer": "BIGINT", "number": "BIGINT DOUBLE DECIMAL FLOAT", "boolean": "BOOLEAN", "array": "ARRAY", "object": "OBJECT"}

CALLS = "conv_id long, turn long, call_id string, name string, arguments string, parents array<string>"
RESULTS = "conv_id long, turn long, call_id string, content string"
SCHEMAS = "name string, field string, kind string, required boolean, closed boolean"


def _first(df: DataFrame, *payload: str) -> DataFrame:
    """The earliest row of each (conv_id, call_id), and how many there are."""
    best = F.min(F.struct("turn", *payload)).alias("b")
    return df.where("conv_id is not null and call_id is not null").groupBy("conv_id", "call_id").agg(best, F.count("*").alias("seen")).select("conv_id", "call_id", "seen", "b.*")


def canonical(text: Column) -> Column:
    """Canonical JSON of a JSON text: keys sorted at every depth, no blanks; null where it is malformed."""
    return F.to_json(F.try_parse_json(text))


def numbered(rows: DataFrame, scratch: Scratch, *order: Column) -> DataFrame:
    """``rows`` with ``gid``: rising in the order, without gaps inside a partition of the sort, 2**33 apart between partitions."""
    # written, so that the numbers stay what they are
    return scratch.write(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("gid", F.monotonically_increasing_id()), "numbered")


def _solved(nodes: Column) -> Column:
    """Levels of the calls of a block, null where a parent's is not known; ``nodes`` are ordered by gid without gaps."""
    none = F.array().cast("array<bigint>")

    def of_base(base: Column) -> Column:
        at = lambda levels, p: F.get(levels, (p - base).cast("int"))

        def level(x: Column, levels: Column) -> Column:
            highest = F.aggregate(x["locals"], x["ahead"], lambda m, p: F.greatest(m, at(levels, p)))
            return F.coalesce(x["level"], F.when(x["free"] & F.forall(x["locals"], lambda p: at(levels, p).isNotNull()), highest + 1))

        def sweeps(first: Column) -> Column:
            missing = lambda levels: F.size(F.filter(levels, lambda v: v.isNull()))
            state = lambda levels, left, moved: F.struct(levels.alias("levels"), left.alias("left"), moved.alias("moved"))

            def sweep(held: Column) -> Column:
                following = F.transform(nodes, lambda x, i: F.coalesce(F.get(held["levels"], i), level(x, held["levels"])))
                return let(following, lambda n: state(n, missing(n), missing(n) < held["left"]))

            whole = F.aggregate(nodes, state(first, missing(first), missing(first) > 0), lambda held, _: F.when(held["moved"] & (held["left"] > 0), sweep(held)).otherwise(held))
            return F.when(missing(first) == 0, first).otherwise(whole["levels"])

        return let(F.aggregate(nodes, none, lambda levels, x: F.concat(levels, F.array(level(x, levels)))), sweeps)

    return let(F.get(nodes, F.lit(0))["gid"], of_base)


def topological_levels(calls: DataFrame, scratch: Scratch, block: int = BLOCK) -> DataFrame:
    """(conv_id, call_id, level) of ``calls(conv_id, call_id, turn, parents)``, keys distinct; level null on and behind cycles.

    A call without (known) parents has level 0, any other one more than its highest parent.
    """
    order = (F.col("conv_id"), F.col("turn").asc_nulls_first(), F.col("call_id"))
    nodes = numbered(calls.select("conv_id", "call_id", "turn", "parents"), scratch, *order)
    keys = nodes.select("conv_id", "call_id", "gid")
    asked = nodes.select("conv_id", "gid", F.explode(F.array_distinct("parents")).alias("parent"))
    edges = asked.join(keys.select("conv_id", F.col("call_id").alias("parent"), F.col("gid").alias("up")), ["conv_id", "parent"])
    near = F.floor(F.col("gid") / block) == F.floor(F.col("up") / block)
    sides = edges.groupBy("gid").agg(F.collect_list(F.when(near, F.col("up"))).alias("locals"), F.collect_list(F.when(~near, F.col("up"))).alias("far"))
    none = F.array().cast("array<bigint>")
    todo = keys.join(sides, "gid", "left").select(
        "conv_id", "gid", F.floor(F.col("gid") / block).alias("block"), F.coalesce("locals", none).alias("locals"), F.coalesce("far", none).alias("far"), F.lit(None).cast("long").alias("level"),
    )
    # parents in other blocks: all known (free), and the highest of them
    todo = todo.withColumns({"free": F.size("far") == 0, "ahead": F.lit(-1).cast("long")})
    finished: list[DataFrame] = []
    left = None
    while True:
        listed = todo.groupBy("conv_id", "block").agg(F.array_sort(F.collect_list(F.struct("gid", "locals", "far", "free", "ahead", "level"))).alias("nodes"))
        solved = listed.select("conv_id", "block", F.explode(F.arrays_zip("nodes", _solved(F.col("nodes")).alias("solved"))).alias("n"))
        out = scratch.write(solved.select("conv_id", "block", "n.nodes.gid", "n.nodes.locals", "n.nodes.far", F.col("n.solved").alias("level")), "solved")
        still = out.agg(F.count(F.when(F.col("level").isNull(), 1))).first()[0]
        if not still or still == left:
            finished.append(out)
            break
        left = still
        some = out.where("level is null").select("conv_id", "block").distinct()
        finished.append(out.join(some, ["conv_id", "block"], "left_anti"))
        if len(finished) > PARTS:
            finished = [scratch.write(_united(finished), "finished")]
        again = out.join(some, ["conv_id", "block"], "left_semi")
        known = _united([*finished, again.select(*out.columns)]).where("level is not null").select(F.col("gid").alias("up"), F.col("level").alias("above"))
        met = again.where("level is null").select("gid", F.explode("far").alias("up")).join(known, "up").groupBy("gid").agg(F.count("*").alias("have"), F.max("above").alias("highest"))
        todo = again.join(met, "gid", "left").withColumns({"free": F.size("far") == F.coalesce("have", F.lit(0)), "ahead": F.coalesce("highest", F.lit(-1))})
    return keys.join(_united(finished).select("gid", "level"), "gid").select("conv_id", "call_id", "level")


def _united(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def dense_position(rows: DataFrame, scratch: Scratch) -> DataFrame:
    """``rows(conv_id, call_id, level, turn)`` with ``position`` from 0 in the order (level, turn, call_id) of each conversation.

    Calls without a level come last.
    """
    order = (F.col("conv_id"), F.col("level").asc_nulls_last(), F.col("turn").asc_nulls_first(), F.col("call_id"))
    ranked = numbered(rows, scratch, *order).withColumn("part", F.shiftright("gid", 33))
    counts = ranked.groupBy("conv_id", "part").agg(F.count("*").alias("here"), F.min("gid").alias("first"))
    before = F.sum("here").over(Window.partitionBy("conv_id").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    offsets = counts.select("conv_id", "part", "first", F.coalesce(before, F.lit(0)).alias("before"))
    return ranked.join(offsets, ["conv_id", "part"]).select(*rows.columns, (F.col("gid") - F.col("first") + F.col("before")).alias("position"))


def validate(calls: DataFrame, schemas: DataFrame) -> DataFrame:
    """``calls`` with ``problem``, null where the arguments fit the schema of their tool.

    kind is one of string, integer, number, boolean, array, object.
    """
    known = F.when(F.col("field").isNotNull(), F.struct("field", "kind", F.coalesce("required", F.lit(False)).alias("required")))
    fields = schemas.where("name is not null").groupBy("name").agg(F.collect_set(known).alias("fields"), F.max(F.coalesce("closed", F.lit(False))).alias("closed"))
    parsed = F.try_parse_json(F.col("arguments"))
    members = F.when(F.schema_of_variant(parsed).startswith("OBJECT"), parsed.cast("map<string,variant>"))
    shapes = F.transform_values(members, lambda _, v: F.regexp_replace(F.schema_of_variant(v), r"[<(].*$", ""))
    named = calls.join(small(fields), "name", "left").withColumn("shapes", shapes)
    kinds = F.create_map(*[F.lit(x) for pair in KINDS.items() for x in pair])
    fits = lambda f: F.array_contains(F.split(F.try_element_at(kinds, f["kind"]), " "), F.try_element_at("shapes", f["field"]))
    names = lambda c: F.transform(c, lambda f: f["field"])
    missing = names(F.filter("fields", lambda f: f["required"] & ~F.map_contains_key("shapes", f["field"])))
    wrong = names(F.filter("fields", lambda f: F.map_contains_key("shapes", f["field"]) & ~F.coalesce(fits(f), F.lit(False))))
    unknown = F.array_except(F.map_keys("shapes"), names("fields"))
    listed = lambda label, c: F.concat(F.lit(label), F.array_join(F.array_sort(c), ","))
    problem = (
        F.when(F.col("fields").isNull(), F.lit("unknown tool"))
        .when(F.col("shapes").isNull(), F.lit("arguments are no object"))
        .when(F.size(missing) > 0, listed("missing ", missing))
        .when(F.size(wrong) > 0, listed("type of ", wrong))
        .when(F.col("closed") & (F.size(unknown) > 0), listed("unknown ", unknown))
    )
    return named.withColumn("problem", problem).drop("fields", "closed", "shapes")


def link_tool_calls(calls: DataFrame, results: DataFrame, schemas: DataFrame) -> DataFrame:
    """One row per distinct call, and one per result whose identifier no call has.

    conv_id, call_id, name, level, position, n_calls and n_results (rows with the
    identifier), problem ("orphan result" for results without a call, "cycle"
    where there is no level), linked and json: the canonical form of the call,
    its result and its turn numbers (null for orphans).
    """
    scratch = Scratch(calls.sparkSession, "tools")
    one = scratch.write(_first(calls, "name", "arguments", "parents").withColumnRenamed("seen", "n_calls"))
    answers = scratch.write(_first(results, "content").select("conv_id", "call_id", F.col("seen").alias("n_results"), F.col("turn").alias("answered"), "content"))
    levels = topological_levels(one, scratch)
    placed = dense_position(levels.join(one.select("conv_id", "call_id", "turn"), ["conv_id", "call_id"]), scratch).select("conv_id", "call_id", "level", "position")
    checked = validate(one.drop("parents"), schemas)
    joined = checked.join(placed, ["conv_id", "call_id"]).join(answers, ["conv_id", "call_id"], "left")
    # fields in alphabetical order; arguments stand as JSON where they are JSON, else as a string
    raw = F.coalesce(canonical(F.col("arguments")), quoted(F.col("arguments")), F.lit("null"))
    number = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("null"))
    text = F.concat(
        F.lit('{"answered":'), number("answered"), F.lit(',"arguments":'), raw, F.lit(',"call_id":'), quoted(F.col("call_id")), F.lit(',"content":'),
        F.coalesce(quoted(F.col("content")), F.lit("null")), F.lit(',"name":'), F.coalesce(quoted(F.col("name")), F.lit("null")), F.lit(',"turn":'), number("turn"), F.lit("}"),
    )
    shown = joined.select(
        "conv_id", "call_id", "name", "level", "position", "n_calls", F.coalesce("n_results", F.lit(0)).cast("long").alias("n_results"),
        F.coalesce("problem", F.when(F.col("level").isNull(), F.lit("cycle"))).alias("problem"), F.col("n_results").isNotNull().alias("linked"), text.alias("json"),
    )
    orphans = answers.join(one.select("conv_id", "call_id"), ["conv_id", "call_id"], "left_anti")
    lost = lambda kind: F.lit(None).cast(kind)
    return shown.unionByName(
        orphans.select(
            "conv_id", "call_id", lost("string").alias("name"), lost("long").alias("level"), lost("long").alias("position"), F.lit(0).cast("long").alias("n_calls"),
            F.col("n_results").cast("long").alias("n_results"), F.lit("orphan result").alias("problem"), F.lit(False).alias("linked"), lost("string").alias("json"),
        )
    )


def quoted(value: Column) -> Column:
    """A string as a JSON string."""
    return F.when(value.isNotNull(), F.regexp_extract(F.to_json(F.struct(value.alias("v"))), r'(?s)^\{"v":(.*)\}$', 1))


def dialogue_events(conversations: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(calls, results, schemas) of ``conversations(conv_id, turn, role, text)``.

    Recorded tool use: a text that is a JSON object with ``tool_calls`` (a list
    of id, name, arguments and, if any, parents) makes calls, and a text of role
    ``tool`` that is an object with ``tool_call_id`` and ``content`` a result.

    Plain dialogue is read as calls of the answering party: a turn of any other
    role than assistant and tool asks it (tool ``ask``, or ``instruct`` for the
    role system, with the arguments chars and text), under the identifier of its
    turn; a turn of the assistant is the result for the turn before it.  A call
    uses the result before it and the instruction right before it.
    """
    told = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    held = F.when(F.ltrim("text").startswith("{"), F.from_json("text", "tool_calls array<struct<id:string,name:string,arguments:string,parents:array<string>>>, tool_call_id string, content string"))
    told = told.withColumn("held", held)
    calling, answering = F.col("held.tool_calls").isNotNull(), (F.col("role") == "tool") & F.col("held.tool_call_id").isNotNull()
    recorded = told.where(calling).select("conv_id", "turn", F.explode("held.tool_calls").alias("c")).select("conv_id", "turn", F.col("c.id").alias("call_id"), "c.name", "c.arguments", "c.parents")
    name = lambda ahead: F.concat(F.lit("turn-"), (F.col("turn") - ahead).cast("string"))
    plain = told.where(~F.coalesce(calling, F.lit(False)) & ~F.coalesce(answering, F.lit(False)))
    asked = plain.where("role is null or role not in ('assistant', 'tool')").select(
        "conv_id", "turn", name(0).alias("call_id"), F.when(F.col("role") == "system", "instruct").otherwise("ask").alias("name"),
        F.to_json(F.struct(F.coalesce(F.length("text"), F.lit(0)).alias("chars"), F.coalesce("text", F.lit("")).alias("text"))).alias("arguments"), F.array(name(2), name(1)).alias("parents"),
    )
    said = plain.where("role in ('assistant', 'tool')").select("conv_id", "turn", name(1).alias("call_id"), F.col("text").alias("content"))
    returned = told.where(answering).select("conv_id", "turn", F.col("held.tool_call_id").alias("call_id"), "held.content")
    schemas = conversations.sparkSession.createDataFrame([(n, f, k, True, True) for n in ("ask", "instruct") for f, k in (("chars", "integer"), ("text", "string"))], SCHEMAS)
    return recorded.unionByName(asked), returned.unionByName(said), schemas


#: DuckDB SQL of the links of plain dialogue (no recorded tool use) in ``conversations``.
ORACLE = """
WITH RECURSIVE calls AS (
  SELECT conv_id, turn, 'turn-' || turn AS call_id, CASE WHEN role = 'system' THEN 'instruct' ELSE 'ask' END AS name, coalesce(text, '') AS text
  FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL AND (role IS NULL OR role NOT IN ('assistant', 'tool'))),
results AS (
  SELECT conv_id, turn AS answered, 'turn-' || (turn - 1) AS call_id, text AS content
  FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL AND role IN ('assistant', 'tool')),
paths(conv_id, turn, level) AS (
  SELECT conv_id, turn, 0::BIGINT FROM calls
  UNION ALL SELECT c.conv_id, c.turn, p.level + 1 FROM calls c JOIN paths p ON c.conv_id = p.conv_id AND c.turn - p.turn IN (1, 2)),
levels AS (SELECT conv_id, turn, max(level) AS level FROM paths GROUP BY conv_id, turn),
placed AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY level, turn) - 1 AS position FROM levels)
SELECT c.conv_id, c.call_id, c.name, p.level, p.position::BIGINT AS position, 1::BIGINT AS n_calls,
  (r.call_id IS NOT NULL)::BIGINT AS n_results, NULL::VARCHAR AS problem, r.call_id IS NOT NULL AS linked,
  '{"answered":' || coalesce(r.answered::VARCHAR, 'null') || ',"arguments":{"chars":' || length(c.text) || ',"text":' || to_json(c.text)::VARCHAR
  || '},"call_id":' || to_json(c.call_id)::VARCHAR || ',"content":' || coalesce(to_json(r.content)::VARCHAR, 'null')
  || ',"name":' || to_json(c.name)::VARCHAR || ',"turn":' || c.turn || '}' AS json
FROM calls c JOIN placed p USING (conv_id, turn) LEFT JOIN results r ON r.conv_id = c.conv_id AND r.call_id = c.call_id
UNION ALL
SELECT r.conv_id, r.call_id, NULL, NULL, NULL, 0, 1, 'orphan result', false, NULL
FROM results r WHERE NOT EXISTS (SELECT 1 FROM calls c WHERE c.conv_id = r.conv_id AND c.call_id = r.call_id)
"""
