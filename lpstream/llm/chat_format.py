"""Chat formatting by minimum-cost role repair.

A conversation is legal when an optional system turn is followed by user and
assistant turns in alternation, starting with the user and ending with the
assistant.  Dynamic programming over that automaton chooses, for each turn in
order, to keep it, to relabel it, to merge it into the turn before, or to insert
empty turns in front of it; the costs are parameters.  Equal costs go to the
repair with fewer turns, then to merging, then to the order of roles.

Scale: each turn is a small matrix of least costs from automaton state to state,
and matrices multiply (minimum over sums), so a conversation may be spread over
any number of partitions.  Turns without their texts are dealt by range of
(conversation, turn, role) and checkpointed; one pass reports a few matrices a
partition, the driver picks the states at the partition borders, a second pass
repairs each partition between its borders.  Texts join the decisions by row;
rows are numbered in a checkpoint, so a row read again has the same number.

Defined cases: null or unknown roles may be relabelled to any at a lower cost;
null turns sort first; a null conversation id is one conversation; null texts
are empty; tied turns go by role, then by text hash; repeated rows are repeated
turns; an empty table gives no rows.  The longest conversation has no limit.
"""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import checkpointed

ROLES = ("system", "user", "assistant")
#: Other names of the roles.
ALIASES = {"human": "user", "prompter": "user", "customer": "user", "bot": "assistant", "model": "assistant", "gpt": "assistant", "ai": "assistant", "chatgpt": "assistant", "instruction": "system", "developer": "system"}
START, SYSTEM, USER, ASSISTANT = range(4)
COUNT = 1 << 40  # costs stand above this, numbers of turns below
NEVER = 1 << 62


@dataclass(frozen=True)
class Costs:
    merge: int = 2
    insert: int = 3
    relabel: int = 5
    name: int = 1  # a role that is missing or unknown gets any name


#: Empty turns needed between two states of a legal sequence (None: impossible).
BRIDGE = {
    (START, SYSTEM): (), (START, USER): (), (START, ASSISTANT): (USER,),
    (SYSTEM, USER): (), (SYSTEM, ASSISTANT): (USER,),
    (USER, ASSISTANT): (), (USER, USER): (ASSISTANT,),
    (ASSISTANT, USER): (), (ASSISTANT, ASSISTANT): (USER,),
}
#: Empty turns needed after the last.
ENDING = {START: (), SYSTEM: (USER, ASSISTANT), USER: (ASSISTANT,), ASSISTANT: ()}


def role_code(role: str | None) -> int:
    """1 to 3 by role, 0 where unknown."""
    r = (role or "").strip().lower()
    r = ALIASES.get(r, r)
    return ROLES.index(r) + 1 if r in ROLES else 0


def step_table(costs: Costs) -> list[list[list[tuple[int, bool, tuple]]]]:
    """[role][from][to]: (cost with turn count, merged, inserted turns)."""
    table = []
    for role in range(4):
        rows = []
        for a in range(4):
            row = [(NEVER, False, ())] * 4
            for b in (SYSTEM, USER, ASSISTANT):
                name = 0 if b == role else costs.name if role == 0 else costs.relabel
                options = []
                if a == b:
                    options.append(((costs.merge + name) * COUNT, True, ()))
                if (a, b) in BRIDGE:
                    new = BRIDGE[a, b]
                    options.append(((costs.insert * len(new) + name) * COUNT + 1 + len(new), False, new))
                if options:
                    row[b] = min(options, key=lambda o: (o[0], not o[1]))
            rows.append(row)
        table.append(rows)
    return table


def ending(costs: Costs) -> list[int]:
    return [len(ENDING[s]) * (costs.insert * COUNT + 1) for s in range(4)]


UNIT = [[0 if a == b else NEVER for b in range(4)] for a in range(4)]


def matrix_of(roles, table) -> list[list[int]]:
    """Least costs from state to state over a run of turns."""
    m = UNIT
    for r in roles:
        t = table[r]
        m = [[min(min(row[k] + t[k][b][0] for k in range(4)), NEVER) for b in range(4)] for row in m]
    return m


def repair(roles: list[int], table, final: list[int], first: int = START, last: int | None = None) -> list[tuple[int, bool, tuple]]:
    """(state, merged, inserted) of each turn on the cheapest path from `first` (to `last`, or to the cheapest ending)."""
    cost = [NEVER] * 4
    cost[first] = 0
    back = []
    for r in roles:
        t = table[r]
        nxt, frm = [NEVER] * 4, [0] * 4
        for b in (SYSTEM, USER, ASSISTANT):
            for a in range(4):
                c = cost[a] + t[a][b][0]
                if c < nxt[b]:
                    nxt[b], frm[b] = c, a
        cost = nxt
        back.append(frm)
    b = last if last is not None else min(range(4), key=lambda s: cost[s] + final[s])
    out = []
    for r, frm in zip(reversed(roles), reversed(back)):
        a = frm[b]
        _, merged, inserted = table[r][a][b]
        out.append((b, merged, inserted))
        b = a
    return out[::-1]


def _runs(batches, seen: dict):
    """Sorted (conversation, role code, row, part) batches to (conversation, roles, rows), a whole run of a partition at a time.

    `seen` gets the part as written at the checkpoint: a task's own number changes in a union.
    """
    now, roles, rows, any_ = None, [], [], False
    for b in batches:
        if b.num_rows:
            seen["part"], seen["type"] = b.column(3)[0].as_py(), b.schema.field(0).type
        for c, r, i in zip(*(b.column(k).to_pylist() for k in range(3))):
            if any_ and c != now:
                yield now, roles, rows
                roles, rows = [], []
            now, any_ = c, True
            roles.append(r)
            rows.append(i)
    if any_:
        yield now, roles, rows


def _name(conversation) -> str | None:
    """A conversation's name to compare at borders: null is none of the others."""
    return None if conversation is None else str(conversation)


def _borders(turns: DataFrame, table) -> list:
    """For each partition: its first and last conversation with the matrices of their runs here."""

    def run(batches):
        first = last = None
        seen: dict = {}
        for c, roles, _ in _runs(batches, seen):
            if first is None:
                first = last = (c, roles)
            else:
                last = (c, roles)
            n = 1 if first is last else 2
        if first is not None:
            flat = lambda x: [v for row in matrix_of(x[1], table) for v in row]
            yield pa.RecordBatch.from_pydict({"part": pa.array([seen["part"]], pa.int32()), "one": pa.array([n == 1]), "c1": pa.array([_name(first[0])], pa.string()), "c2": pa.array([_name(last[0])], pa.string()), "m1": pa.array([flat(first)], pa.list_(pa.int64())), "m2": pa.array([flat(last)], pa.list_(pa.int64()))})

    return turns.mapInArrow(run, "part int, one boolean, c1 string, c2 string, m1 array<long>, m2 array<long>").orderBy("part").collect()


def _plan(found: list, final: list[int]) -> dict[int, tuple]:
    """part -> (entry state, turns before, goes on after, exit state): the states of conversations that cross partitions."""
    square = lambda v: [list(v[4 * a : 4 * a + 4]) for a in range(4)]
    plan = {r.part: [START, 0, False, None] for r in found}
    i = 0
    while i < len(found):
        # The conversation that ends partition i, and the partitions over which it goes on.
        chain = [(found[i].part, square(found[i].m2))]
        j = i + 1
        while j < len(found) and found[j].c1 == found[i].c2:
            chain.append((found[j].part, square(found[j].m1)))
            j += 1
            if not found[j - 1].one:
                break
        n = len(chain)
        ahead = [final] * (n + 1)  # least cost from each border to the end
        for k in range(n - 1, 0, -1):
            ahead[k] = [min(chain[k][1][a][b] + ahead[k + 1][b] for b in range(4)) for a in range(4)]
        state, before = START, 0
        for k, (part, m) in enumerate(chain):
            if k:
                plan[part][:2] = state, before
            if k < n - 1:
                nxt = min(range(4), key=lambda b: (m[state][b] + ahead[k + 1][b], b))
                before += m[state][nxt] % COUNT
                plan[part][2:] = True, nxt
                state = nxt
        # The last partition of a chain may end with another conversation, which may go on too.
        i = i + n - 1 if n > 1 and not found[i + n - 1].one else i + n
    return {p: tuple(v) for p, v in plan.items()}


def decide(conversations: DataFrame, costs: Costs = Costs(), conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", parts: int | None = None):
    """Decisions (row, conv_id, position, role, op, source_order) and the numbered input they refer to.

    `row` and `source_order` (the rank of a row in the order of turns, ties included)
    are null for inserted turns.  `position` counts repaired turns of the
    conversation; merged rows share the position of the turn they go into.
    """
    spark = conversations.sparkSession
    table, final = step_table(costs), ending(costs)
    numbered = conversations.select(F.col(conv_col).alias("conv_id"), F.col(turn_col).alias("turn"), F.col(role_col).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("row", F.monotonically_increasing_id())
    numbered = checkpointed(numbered)
    name = F.trim(F.lower(F.coalesce("role", F.lit(""))))
    code = F.lit(0)
    for k, r in enumerate(ROLES):
        code = F.when(name.isin(r, *[a for a, x in ALIASES.items() if x == r]), k + 1).otherwise(code)
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    order = ["conv_id", "turn", "code", "h", "row"]
    turns = checkpointed(numbered.select("conv_id", "turn", code.alias("code"), F.xxhash64("text").alias("h"), "row").repartitionByRange(parts, *order).sortWithinPartitions(*order).select("conv_id", "code", "row", F.spark_partition_id().alias("part")))
    plan = _plan(_borders(turns, table), final)
    kind = turns.schema["conv_id"].dataType.simpleString()

    def run(batches):
        seen: dict = {}
        kept = None
        order = 0

        def rows_of(c, roles, rows, first, start, last, open_):
            nonlocal order
            path = repair(roles, table, final, first, last)
            out, position = [], start
            for (state, merged, inserted), i, r in zip(path, rows, roles):
                for s in inserted:
                    position += 1
                    out.append((c, None, position, ROLES[s - 1], "insert", None))
                position += not merged
                out.append((c, i, position, ROLES[state - 1], ("merge" if merged else "keep") if r == state else ("merge+relabel" if merged else "relabel"), (seen["part"] << 40) + order))
                order += 1
            if not open_:
                for s in ENDING[path[-1][0]]:
                    position += 1
                    out.append((c, None, position, ROLES[s - 1], "insert", None))
            return out

        def batch(rows, conv_type):
            cols = list(zip(*rows))
            return pa.RecordBatch.from_arrays([pa.array(cols[0], conv_type), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64()), pa.array(cols[3]), pa.array(cols[4]), pa.array(cols[5], pa.int64())], names=["conv_id", "row", "position", "role", "op", "source_order"])

        first, buffer = True, []
        for c, roles, rows in _runs(batches, seen):
            entry, before, goes_on, leave = plan[seen["part"]]
            if kept is not None:
                buffer += rows_of(*kept[0], *kept[1], None, False)
                if len(buffer) > 4096:
                    yield batch(buffer, seen["type"])
                    buffer = []
            kept = ((c, roles, rows), (entry, before) if first else (START, 0))
            first = False
        if kept is not None:
            buffer += rows_of(*kept[0], *kept[1], leave, goes_on)
        if buffer:
            yield batch(buffer, seen["type"])

    return numbered, turns.mapInArrow(run, f"conv_id {kind}, row long, position long, role string, op string, source_order long")


def format_chat(conversations: DataFrame, costs: Costs = Costs(), parts: int | None = None, **columns) -> DataFrame:
    """One row a source turn or inserted turn, rendered.

    conv_id, position (turn of the repaired conversation), turn (as read), role,
    op (keep, relabel, merge, merge+relabel, insert), source_order, rendered.  A
    conversation is the `rendered` pieces in order of (position, source_order); a
    merged row continues the turn before it.
    """
    numbered, decisions = decide(conversations, costs, parts=parts, **columns)
    texts = numbered.select("row", "turn", "text")
    # Inserted turns have no row to join: they keep out of the join, so no common null key gathers them.
    joined = decisions.filter("row is not null").join(texts, "row")
    head = F.concat(F.lit("<|"), F.col("role"), F.lit("|>\n"))
    real = joined.select("conv_id", "position", "turn", "role", "op", "source_order", F.when(F.col("op").startswith("merge"), F.concat(F.lit("\n"), "text")).otherwise(F.concat(F.when(F.col("position") > 1, "\n").otherwise(""), head, F.col("text"))).alias("rendered"))
    added = decisions.filter("row is null").select("conv_id", "position", F.lit(None).cast(texts.schema["turn"].dataType).alias("turn"), "role", "op", "source_order", F.concat(F.when(F.col("position") > 1, "\n").otherwise(""), head).alias("rendered"))
    return real.unionByName(added)
