"""Chat formatting: the cheapest repair of a conversation's roles, then its rendering.

The legal-turn automaton allows an optional system turn first, then user and assistant in turn, ending
with assistant. Its state is the role of the last turn. A turn may be kept, relabelled, merged into the
turn before it, or preceded by an empty turn, each at a cost; dynamic programming finds the cheapest legal sequence.

A turn is a 4 x 4 matrix of costs in the (min, +) semiring, so runs of turns can be reduced apart: a conversation is
cut into blocks of BLOCK_TURNS turns by rank, the blocks' matrices fix each block's entry and
exit state, and each block is then repaired and rendered by itself. Blocks of a very long conversation are reduced in turn
by runs of BLOCK_TURNS. Ranks are only needed in conversations of more than one block; there the turns are
sorted over all machines (equal turns in any order), so no task gathers a conversation, whatever its turn numbers are.

Edge cases: turns stand in the order of turn, role and a hash of the text, nulls first. A null or unknown role is relabelled, a null text is
empty. Repeated rows are turns of their own. Rows with a null conv_id form one conversation. Extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gainbound.llm.common import settle, small_join

BLOCK_TURNS = 1024
ROLES = ("system", "user", "assistant")
#: States are 0 for the start and 1 + a role's place in ROLES.
LEGAL = {(0, 1), (0, 2), (1, 2), (2, 3), (3, 2)}
MERGE, RELABEL, INSERT = 1, 2, 3
END_MARK = "<|end|>\n"
_FAR = 1 << 40


def _moves(role: str | None) -> list[tuple[int, int, int, str, int]]:
    """All options for a turn: state before, state after, cost, what is done, state of an inserted turn or 0; the first of equals is preferred."""
    out = []
    for before in range(4):
        for after in (1, 2, 3):
            price, label = (0, "keep") if role == ROLES[after - 1] else (RELABEL, "relabel")
            if (before, after) in LEGAL:
                out.append((before, after, price, label, 0))
            if before == after:
                out.append((before, after, price + MERGE, "merge", 0))
            for between in (1, 2, 3):
                if (before, between) in LEGAL and (between, after) in LEGAL and (before, after) not in LEGAL:
                    out.append((before, after, price + INSERT, label, between))
    return sorted(out, key=lambda m: (m[2], bool(m[4]), m[3] != "keep", m[3]))


_MOVES = {r: _moves(r) for r in (*ROLES, None)}
#: Cost of a legal end from each state, and the empty turns that it takes.
_END = {0: (0, ()), 1: (2 * INSERT, (2, 3)), 2: (INSERT, (3,)), 3: (0, ())}


def _known(role: str | None) -> str | None:
    return role if role in ROLES else None


def step(ahead: list[int], role: str | None) -> list[int]:
    """Least cost from each state before a turn, given the costs after it."""
    out = [_FAR] * 4
    for before, after, price, _, _ in _MOVES[_known(role)]:
        out[before] = min(out[before], price + ahead[after])
    return out


def matrix(roles: list[str | None]) -> list[int]:
    """Row-major least costs from each entry state to each exit state."""
    columns = []
    for out in range(4):
        ahead = [0 if s == out else _FAR for s in range(4)]
        for role in reversed(roles):
            ahead = [min(x, _FAR) for x in step(ahead, role)]
        columns.append(ahead)
    return [columns[o][i] for i in range(4) for o in range(4)]


def product(matrices: list[list[int]]) -> list[int]:
    """The costs of blocks one after the other."""
    out = matrices[0]
    for m in matrices[1:]:
        out = [min(min(out[4 * i + k] + m[4 * k + o] for k in range(4)), _FAR) for i in range(4) for o in range(4)]
    return out


def repair(turns: list[tuple[str | None, str | None]], entry: int, leave: int, last: bool) -> tuple[int, int, str, dict[str, int]]:
    """Cost, turns begun, rendering and counts of actions of a block that is entered and left in given states."""
    ahead = [[0 if s == leave else _FAR for s in range(4)]]
    for role, _ in reversed(turns):
        ahead.append([min(x, _FAR) for x in step(ahead[-1], role)])
    ahead.reverse()
    state, cost, begun, done = entry, 0, 0, {"keep": 0, "relabel": 0, "merge": 0, "insert": 0}
    pieces: list[str] = []

    def begin(role: int, text: str) -> None:
        nonlocal begun
        if begun or entry:
            pieces.append(END_MARK)
        begun += 1
        pieces.append(f"<|{ROLES[role - 1]}|>\n{text}")

    for i, (role, text) in enumerate(turns):
        for before, after, price, label, between in _MOVES[_known(role)]:
            if before == state and price + ahead[i + 1][after] == ahead[i][state]:
                break
        if between:
            begin(between, "")
            done["insert"] += 1
        if label == "merge":
            pieces.append("\n" + (text or ""))
        else:
            begin(after, text or "")
        done[label] += 1
        cost += price
        state = after
    if last:
        for role in _END[state][1]:
            begin(role, "")
            done["insert"] += 1
        cost += _END[state][0]
        if begun or entry:
            pieces.append(END_MARK)
    return cost, begun, "".join(pieces), done


def _grouped(batches, key):
    held, at = [], None
    for batch in batches:
        for r in batch.to_pylist():
            if held and key(r) != at:
                yield held
                held = []
            at = key(r)
            held.append(r)
    if held:
        yield held


def _frame(rows: list[dict], kinds: pa.Schema):
    return pa.RecordBatch.from_pylist(rows, kinds)


def _batched(rows, kinds: pa.Schema, most: int = 512):
    held = []
    for r in rows:
        held.append(r)
        if len(held) >= most:
            yield _frame(held, kinds)
            held = []
    if held:
        yield _frame(held, kinds)


def _match(left: DataFrame, right: DataFrame, keys: list[str], rows: int) -> DataFrame:
    """A left join on keys of which any may be null; right has one row of each key."""
    other = right.toDF(*(f"_{c}" if c in keys else c for c in right.columns))
    on = None
    for k in keys:
        same = F.col(k).eqNullSafe(F.col(f"_{k}"))
        on = same if on is None else on & same
    return small_join(left, other, on, "left", rows, 64).drop(*(f"_{k}" for k in keys))


def blocked(turns: DataFrame, block_turns: int) -> DataFrame:
    """turns with `block`: the turn's rank in its conversation over block_turns."""
    long = settle(turns.groupBy("conv_id").agg(F.count("*").alias("_n")).where(F.col("_n") > block_turns))
    n = long.count()
    if not n:
        return turns.withColumn("block", F.lit(0).cast("long"))
    marked = _match(turns, long, ["conv_id"], n)
    order = ["conv_id", "turn", "role", "_text", "_any"]
    # equal turns are told apart by chance, so that a turn that very many rows have is spread as well
    mixed = marked.where("_n is not null").withColumn("_text", F.xxhash64("text")).withColumn("_any", F.rand(7))
    lined = settle(mixed.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_row", F.monotonically_increasing_id()).withColumn("_part", F.spark_partition_id()))
    runs = lined.groupBy("conv_id", "_part").agg(F.min("_row").alias("_first"), F.count("*").alias("_here"))
    # a row for each task that has turns of a conversation
    runs = runs.withColumn("_before", F.sum("_here").over(Window.partitionBy("conv_id").orderBy("_part")) - F.col("_here"))
    runs = settle(runs.select("conv_id", "_part", (F.col("_before") - F.col("_first")).alias("_shift")))
    ranked = _match(lined.withColumnRenamed("_part", "part_"), runs.withColumnRenamed("_part", "part_"), ["conv_id", "part_"], runs.count())
    placed = ranked.withColumn("block", F.floor((F.col("_row") + F.col("_shift")) / block_turns).cast("long"))
    columns = [*turns.columns, "block"]
    return marked.where("_n is null").withColumn("block", F.lit(0).cast("long")).select(*columns).union(placed.select(*columns))


def repair_roles(conversations: DataFrame, block_turns: int = BLOCK_TURNS, block_runs: int = BLOCK_TURNS) -> DataFrame:
    """conv_id, part (from 0), n_turns, n_rendered, the counts of actions, cost and rendered, for each block of each conversation.

    The parts of a conversation, joined in order, are its rendering; a turn that goes on in the next part is closed there."""
    from pyspark.sql.pandas.types import to_arrow_type

    kind = conversations.schema["conv_id"].dataType
    conv, name = to_arrow_type(kind), kind.simpleString()
    rows = blocked(conversations.select("conv_id", "turn", "role", "text"), block_turns)
    counted = ["keep", "relabel", "merge", "insert"]
    one = pa.schema([("conv_id", conv), ("block", pa.int64()), ("costs", pa.list_(pa.int64()))])
    two = pa.schema([("conv_id", conv), ("block", pa.int64()), ("part", pa.int64()), ("entry", pa.int32()), ("leave", pa.int32()), ("last", pa.bool_())])
    three = pa.schema([("conv_id", conv), ("part", pa.int64()), ("n_turns", pa.int64()), ("n_rendered", pa.int64()), *((f"n_{c}", pa.int64()) for c in counted), ("cost", pa.int64()), ("rendered", pa.string())])

    def reduce(batches):
        groups = _grouped(batches, lambda r: (r["conv_id"], r["block"]))
        yield from _batched(({"conv_id": g[0]["conv_id"], "block": g[0]["block"], "costs": matrix([r["role"] for r in g])} for g in groups), one)

    def fold(batches):
        """The product of a run of blocks, as the costs of one."""
        for_run = _grouped(batches, lambda r: (r["conv_id"], r["run"]))
        yield from _batched(({"conv_id": g[0]["conv_id"], "block": g[0]["run"], "costs": product([r["costs"] for r in g])} for g in for_run), one)

    def route(batches):
        def all_rows():
            for g in _grouped(batches, lambda r: (r["conv_id"], r["run"])):
                state, goal, closing = g[0]["entry"], g[0]["leave"], g[0]["last"]
                # a run that isn't the last one must end in its given state
                ahead = [_END[s][0] for s in range(4)] if goal is None else [0 if s == goal else _FAR for s in range(4)]
                after = []
                for r in reversed(g):
                    after.append(ahead)
                    ahead = [min(r["costs"][4 * i + o] + ahead[o] for o in range(4)) for i in range(4)]
                for k, (r, ahead) in enumerate(zip(g, reversed(after), strict=True)):
                    leave = min(range(4), key=lambda o: (r["costs"][4 * state + o] + ahead[o], o))
                    yield {"conv_id": r["conv_id"], "block": r["block"], "part": r["block"], "entry": state, "leave": leave, "last": closing and k == len(g) - 1}
                    state = leave

        yield from _batched(all_rows(), two)

    def render(batches):
        def all_rows():
            for g in _grouped(batches, lambda r: (r["conv_id"], r["block"])):
                h = g[0]
                cost, begun, text, done = repair([(r["role"], r["text"]) for r in g], h["entry"], h["leave"], h["last"])
                yield {"conv_id": h["conv_id"], "part": h["part"], "n_turns": len(g), "n_rendered": begun, "cost": cost, "rendered": text} | {f"n_{c}": done[c] for c in counted}

        yield from _batched(all_rows(), three)

    order = ["conv_id", "block", "turn", "role"]
    costs_of, states_of = f"conv_id {name}, block long, costs array<long>", f"conv_id {name}, block long, part long, entry int, leave int, last boolean"
    costs = settle(rows.select(*order).repartition("conv_id", "block").sortWithinPartitions(*order).mapInArrow(reduce, costs_of))

    def routed_of(level: DataFrame) -> DataFrame:
        """States of the blocks of a level: by whole conversations, or by runs whose own states come from the level above."""
        whole = F.lit(0).cast("int").alias("entry"), F.lit(None).cast("int").alias("leave"), F.lit(True).alias("last")
        if level.where(F.col("block") >= block_runs).isEmpty():
            given = level.select("*", F.lit(0).cast("long").alias("run"), *whole)
        else:
            runs = level.withColumn("run", F.floor(F.col("block") / block_runs).cast("long"))
            above = settle(runs.repartition("conv_id", "run").sortWithinPartitions("conv_id", "run", "block").mapInArrow(fold, costs_of))
            states = settle(routed_of(above).select("conv_id", F.col("block").alias("run"), "entry", F.when(~F.col("last"), F.col("leave")).alias("leave"), "last"))
            given = _match(runs, states, ["conv_id", "run"], states.count())
        return given.repartition("conv_id", "run").sortWithinPartitions("conv_id", "run", "block").mapInArrow(route, states_of)

    routed = settle(routed_of(costs))
    both = _match(rows, routed, ["conv_id", "block"], routed.count())
    both = both.withColumn("_text", F.xxhash64("text"))
    return both.repartition("conv_id", "block").sortWithinPartitions(*order, "_text").mapInArrow(
        render, f"conv_id {name}, part long, n_turns long, n_rendered long, " + ", ".join(f"n_{c} long" for c in counted) + ", cost long, rendered string"
    )
