"""Execution models: where the structure lives between rounds, and what crosses the network.

All give the same states. They differ in cost:

``reshuffle``     vertex records with their edges go through a shuffle and storage each round
``reduce_merge``  messages travel; the structure is merged after the shuffle and rewritten
``colocated``     structure and state, split alike on disk, are joined in place; state is rewritten
``resident``      the structure is loaded once and kept; only messages travel
``auto``          picks by memory need and number of rounds

A round's counts come with the state it makes. What it sent and wrote is read from the
counters of its stages: rows through exchanges after the combiner, bytes, and what went
to tables or checkpoints.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop import session
from netprop.operators.graphs import Graph, adjacency_form
from netprop.operators.program import VertexProgram
from netprop.sources import tables


#: Rounds of a run of fixed length, unless it says otherwise; what a loop is sent at its end.
ROUNDS, DONE = 10, -1
#: Hubs up to which their ids are broadcast for salting.
BROADCAST_HUBS = 1_000_000


@dataclass(frozen=True)
class EngineOptions:
    partitions: int | None = None
    combine: bool = True
    #: Above 0: messages to vertices of more than ``hub_degree`` in-edges are summed in so many parts first.
    salt: int = 0
    hub_degree: int = 100_000
    storage: str = "MEMORY_AND_DISK"
    jobs: int = 2
    #: Senders up to which a round's frontier is broadcast (counted the round before; 0: never).
    small_frontier: int = 10_000
    #: The resident engine writes its state to the shared folder every so many rounds, as a start for what lost executors held.
    checkpoint_every: int = 5

    def sized(self, spark: SparkSession) -> EngineOptions:
        return self if self.partitions else replace(self, partitions=int(spark.conf.get("spark.sql.shuffle.partitions")))


@dataclass
class RunResult:
    state: DataFrame
    trace: list[dict] = field(default_factory=list)
    rounds: int = 0
    halted: bool = False
    exchanges: int = 0
    plan: DataFrame | None = None

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        from netprop import schemas

        rows = [tuple(t.get(f.name) for f in schemas.TRACE) for t in self.trace]
        return spark.createDataFrame(rows, schemas.TRACE)


def _counts(state: DataFrame, program: VertexProgram) -> tuple[int, int, int]:
    """Senders of the next round, messages of this one, improved vertices: one pass over the state, which also makes it."""
    r = state.agg(F.sum(program.sending().cast("long")).alias("a"), F.sum("_got").alias("m"), F.sum(F.col("_improved").cast("long")).alias("i")).first()
    return r.a or 0, r.m or 0, r.i or 0


class Engine:
    name = ""
    #: Shuffle exchanges in the plan of the last round.
    exchanges = 0

    def run(self, graph: Graph, program: VertexProgram, state: DataFrame, max_rounds: int | None = None, stop: str = "quiescent", options: EngineOptions | None = None) -> RunResult:
        """``state``: ``id`` and the program's state columns (and perhaps ``_active``) of every vertex.

        ``stop``: 'fixed' runs ``max_rounds`` rounds (10); 'quiescent' ends when no vertex has a message to send,
        or after ``max_rounds`` where that is given: then ``halted`` says which it was.
        """
        if stop not in ("fixed", "quiescent"):
            raise ValueError("stop is 'fixed' or 'quiescent'")
        if stop == "fixed" and max_rounds is None:
            max_rounds = ROUNDS
        spark = state.sparkSession
        options = (options or EngineOptions()).sized(spark)
        result = RunResult(state)
        run_id = uuid.uuid4().hex[:12]
        base = {"run_id": run_id, "problem": program.name, "engine": self.name, "graph": graph.name, "cores": spark.sparkContext.defaultParallelism, "partitions": options.partitions}
        loop = self._loop(graph, program, state, options)

        def round_of(number: int, ask: int | None) -> tuple[int, int, int]:
            began = time.perf_counter()
            with session.measured(spark) as seen:
                senders, messages, improved, rows, more = loop.send(ask)
                took = int(1000 * (time.perf_counter() - began))
            counts = {"active": senders if ask is None else ask, "messages": messages, "improved": improved, "stored_rows": rows, "stored_bytes": seen["written_bytes"] + more}
            result.trace.append(base | {"round": number, "ms": took, "shuffle_rows": seen["shuffle_rows"], "shuffle_bytes": seen["shuffle_bytes"]} | counts)
            return senders

        try:
            with session.loop_conf(spark, options.partitions):
                senders = round_of(0, None)
                number = 0
                while (max_rounds is None or number < max_rounds) and (stop == "fixed" or senders):
                    number += 1
                    senders = round_of(number, senders)
                    result.rounds = number
                result.halted = not senders
                result.state, result.plan = loop.send(DONE)
                result.exchanges = self.exchanges
        finally:
            loop.close()
        return result

    def _loop(self, graph: Graph, program: VertexProgram, state: DataFrame, options: EngineOptions):
        """A generator. First, and for each number of senders sent to it, it yields (senders of the next round, messages,
        improved vertices, rows stored, bytes stored besides what the jobs report); for DONE, (state, last plan).
        A record that holds edges counts as a row and one for each. What the loop made goes when it is closed.
        """
        raise NotImplementedError


def _public(state: DataFrame, program: VertexProgram) -> DataFrame:
    return state.select("id", *program.state)


def _combined(messages: DataFrame, program: VertexProgram, options: EngineOptions, hubs: DataFrame | None = None) -> DataFrame:
    """Messages per receiver. With the combiner, partial sums precede the one exchange; without, every message crosses it.

    Messages to hubs are first summed in parts, dealt by a hash of the sender (``_salt``): a task that runs again deals them alike.
    """
    if not options.combine:
        return program.combined(messages.repartition(options.partitions, "dst"))
    if not options.salt or hubs is None:
        return program.combined(messages)
    dealt = messages.join(hubs, "dst", "left").withColumn("_part", F.when(F.col("_hub"), F.col("_salt")).otherwise(F.lit(0)))
    from netprop.operators.program import COMBINERS

    parts = dealt.groupBy("dst", "_part").agg(*[COMBINERS[how](c).alias(c) for c, how in program.combine.items()], F.count("*").alias("_n"))
    return parts.groupBy("dst").agg(*[COMBINERS[how](c).alias(c) for c, how in program.combine.items()], F.sum("_n").alias("_n"))


def hub_flags(graph: Graph, degree: int) -> DataFrame:
    return graph.edges.groupBy("dst").agg(F.count("*").alias("_k")).where(F.col("_k") > degree).select("dst", F.lit(True).alias("_hub"))


class Resident(Engine):
    """Supersteps over a structure kept in executor memory (or disk, where it does not fit).

    The state is kept too, and written only every ``checkpoint_every`` rounds.
    """

    name = "resident"

    def _loop(self, graph, program, state, options):
        spark, level, n = state.sparkSession, getattr(StorageLevel, options.storage), options.partitions
        structure = graph.edges.select("src", "dst", "w").repartition(n, "src").sortWithinPartitions("src").persist(level)  # sorted once, not in the join of each round
        hubs = hub_flags(graph, options.hub_degree).persist(level) if options.salt else None
        kept, files, plan = [structure, *([hubs] if hubs is not None else [])], [], None
        try:
            structure.count()
            if hubs is not None and hubs.count() <= BROADCAST_HUBS:
                hubs = F.broadcast(hubs)  # counted; else messages would have to travel to learn that they go to a hub
            held = program.fresh(state.repartition(n, "id")).persist(level)
            kept.append(held)
            senders, _, _ = _counts(held, program)
            vertices, now, number, stored = held.count(), session.cut(held), 0, (0, 0)
            ask = yield (senders, 0, 0, *stored)
            while ask != DONE:
                number += 1
                front = now.where(program.sending())
                if options.small_frontier and ask <= options.small_frontier and ask * 20 < vertices:
                    front = F.broadcast(front)  # its rows were counted in the round before
                joined = structure.join(front, F.col("src") == F.col("id"))
                salt = [F.pmod(F.xxhash64("src"), F.lit(options.salt)).cast("int").alias("_salt")] if options.salt else []
                got = _combined(program.messages(joined, *salt), program, options, hubs).withColumnRenamed("dst", "_to")
                plan = program.stepped(now.join(got, F.col("id") == F.col("_to"), "left"))
                self.exchanges = count_exchanges(plan)
                new = plan.persist(level)
                kept.append(new)
                counts = _counts(new, program)
                stored = (0, 0)
                if number % options.checkpoint_every:
                    now = session.cut(new)
                else:
                    session.shared_dir(spark)
                    now = new.checkpoint(eager=True)
                    files.append(session.checkpoint_path(now))
                    stored = (vertices, session.size_of(spark, files[-1]) if files[-1] else 0)
                    if len(files) > 1 and files[-2]:
                        session.remove(spark, files[-2])
                held.unpersist()
                held = new
                ask = yield (*counts, *stored)
            yield session.stored(_public(now, program), "state"), plan
        finally:
            for df in kept:
                df.unpersist()
            if files and files[-1]:
                session.remove(spark, files[-1])


class Colocated(Engine):
    """Structure and state in tables bucketed alike: joined in place, without an exchange; only the state is rewritten."""

    name = "colocated"

    def _loop(self, graph, program, state, options):
        spark, n = state.sparkSession, options.partitions
        names = [tables.bucketed_name(x) for x in ("edges", "state_a", "state_b")]
        try:
            structure = tables.save_bucketed(graph.edges.select("src", "dst", "w"), names[0], n, "src")
            now = tables.save_bucketed(program.fresh(state), names[1], n, "id")
            senders, _, _ = _counts(now, program)
            rows, plan, number = now.count(), None, 0
            ask = yield senders, 0, 0, rows + structure.count(), 0
            while ask != DONE:
                number += 1
                joined = structure.join(now.where(program.sending()).hint("MERGE"), F.col("src") == F.col("id"))
                got = _combined(program.messages(joined), program, options).withColumnRenamed("dst", "_to")
                plan = program.stepped(now.join(got.hint("MERGE"), F.col("id") == F.col("_to"), "left"))
                self.exchanges = count_exchanges(plan)
                now = tables.save_bucketed(plan, names[1 + number % 2], n, "id")
                ask = yield (*_counts(now, program), rows, 0)
            yield session.stored(_public(now, program), "state"), plan
        finally:
            tables.drop(spark, names)


class ReduceMerge(Engine):
    """Messages are combined first, then merged with the vertex records of their bucket, which are rewritten with their edges."""

    name = "reduce_merge"

    def _loop(self, graph, program, state, options):
        spark, n = state.sparkSession, options.partitions
        names = [tables.bucketed_name(x) for x in ("records_a", "records_b")]
        try:
            lists = adjacency_form(graph)
            none = F.array().cast("array<struct<dst:bigint,w:double>>")
            records = program.fresh(state).join(lists, "id", "left").withColumn("adj", F.coalesce("adj", none))
            now = tables.save_bucketed(records, names[0], n, "id")
            senders, _, _ = _counts(now, program)
            rows, plan, number = now.count() + graph.edges.count(), None, 0
            ask = yield senders, 0, 0, rows, 0
            while ask != DONE:
                number += 1
                sent = now.where(program.sending()).select("id", *program.state, F.explode("adj").alias("e")).select("id", *program.state, "e.dst", "e.w")
                got = _combined(program.messages(sent), program, options).withColumnRenamed("dst", "_to")
                plan = program.stepped(now.join(got.hint("MERGE"), F.col("id") == F.col("_to"), "left"), ("adj",))
                self.exchanges = count_exchanges(plan)
                now = tables.save_bucketed(plan, names[number % 2], n, "id")
                ask = yield (*_counts(now, program), rows, 0)
            yield session.stored(_public(now, program), "state"), plan
        finally:
            tables.drop(spark, names)


class Reshuffle(Engine):
    """The whole graph travels each round: each vertex sends messages and its own record, which the receivers tell apart.

    With ``jobs=2`` a first job joins structure and state, shuffling both, and stores what the second job reads.
    """

    name = "reshuffle"

    def _loop(self, graph, program, state, options):
        spark, n = state.sparkSession, options.partitions
        store, between, fixed = (tables.RoundStore(spark, x) for x in ("records", "joined", "structure"))
        try:
            lists = adjacency_form(graph)
            none = F.array().cast("array<struct<dst:bigint,w:double>>")
            size = graph.edges.count()
            if options.jobs == 2:
                edges = fixed.put(0, lists)
                now = store.put(0, program.fresh(state))
            else:
                now = store.put(0, program.fresh(state).join(lists, "id", "left").withColumn("adj", F.coalesce("adj", none)))
            senders, _, _ = _counts(now, program)
            rows, plan, number = now.count(), None, 0
            own = list(program.state)
            ask = yield senders, 0, 0, rows + size + (rows if options.jobs == 2 else 0), 0
            while ask != DONE:
                number += 1
                records = now
                if options.jobs == 2:
                    records = between.put(number, edges.hint("MERGE").join(now, "id", "right").withColumn("adj", F.coalesce("adj", none)))
                send = program.sending()
                out = records.where(send).select("id", *own, F.explode("adj").alias("e")).select("id", *own, "e.dst", "e.w")
                messages = program.messages(out).select(F.col("dst").alias("id"), *program.payload, F.lit(None).cast(records.select(F.struct("_active", *own, *(["adj"] if options.jobs == 1 else []))).schema[0].dataType).alias("_self"))
                selves = records.select("id", *[F.lit(None).cast(messages.schema[c].dataType).alias(c) for c in program.payload], F.struct("_active", *own, *(["adj"] if options.jobs == 1 else [])).alias("_self"))
                met = messages.unionByName(selves).repartition(n, "id")
                from netprop.operators.program import COMBINERS

                folded = met.groupBy("id").agg(F.first("_self", ignorenulls=True).alias("_self"), *[COMBINERS[how](c).alias(c) for c, how in program.combine.items()], F.sum(F.col("_self").isNull().cast("long")).alias("_n"))
                folded = folded.where("_self is not null").select("id", "_n", *program.payload, *[F.col(f"_self.{c}").alias(c) for c in own], *([F.col("_self.adj").alias("adj")] if options.jobs == 1 else []))
                plan = program.stepped(folded, ("adj",) if options.jobs == 1 else ())
                self.exchanges = count_exchanges(plan)
                now = store.put(number, plan)
                ask = yield (*_counts(now, program), rows + size + (rows if options.jobs == 2 else 0), 0)
            yield session.stored(_public(now, program), "state"), plan
        finally:
            for x in (store, between, fixed):
                session.remove(spark, x.root)


# ------------------------------------------------------------------------ choice


def memory_need(vertices: int, edges: int, program: VertexProgram, messages: int | None = None, overhead: float = 1.5) -> int:
    """Bytes that the resident model keeps: structure, two versions of the state, the peak of combined messages."""
    wide = lambda n: 16 + 8 * n
    structure = edges * (16 if "w" not in program.options.get("uses", "w") else 24)
    peak = min(messages if messages is not None else edges, vertices) * wide(len(program.payload))
    return int(overhead * (structure + 2 * vertices * wide(len(program.state)) + peak))


def cache_overhead(spark: SparkSession, edges: DataFrame, k: int = 100) -> float:
    """Bytes that the cache takes for a byte of plain columns, measured on one edge in ``k``."""
    some = edges.select("src", "dst", "w").where(F.pmod(F.xxhash64("src", "dst"), F.lit(k)) == 0).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        before = {i.id(): i.memSize() + i.diskSize() for i in spark.sparkContext._jsc.sc().getRDDStorageInfo()}
        rows = some.count()
        after = {i.id(): i.memSize() + i.diskSize() for i in spark.sparkContext._jsc.sc().getRDDStorageInfo()}
        return (sum(after.values()) - sum(before.get(i, 0) for i in after)) / (24 * rows) if rows else 1.0
    finally:
        some.unpersist()


def storage_memory(spark: SparkSession) -> int:
    """Bytes for keeping and computing, over all executors."""
    return sum(int(spark.sparkContext._jsc.sc().getExecutorMemoryStatus().apply(k)._1()) for k in _executors(spark))


def _executors(spark: SparkSession) -> list:
    keys = spark.sparkContext._jsc.sc().getExecutorMemoryStatus().keySet().toSeq()
    return [keys.apply(i) for i in range(keys.size())]


def choose_engine(vertices: int, edges: int, program: VertexProgram, memory: int, rounds: int, control: bool = False) -> tuple[str, str]:
    """Name of the engine and why."""
    if control:
        return "reshuffle", "asked for as the control"
    if rounds <= 2:
        return "colocated", "two rounds or fewer do not repay loading the structure into memory"
    need = memory_need(vertices, edges, program)
    if need <= memory:
        return "resident", f"structure, states and messages need {need} bytes and {memory} are there"
    return "colocated", f"{need} bytes are needed and {memory} are there: the structure stays on disk, split as the messages are"


def min_feasible(vertices: int, edges: int, program: VertexProgram, worker_memory: int) -> int:
    """Fewest workers of so much memory on which the resident model runs without spilling."""
    return max(1, -(-memory_need(vertices, edges, program) // worker_memory))


class Auto(Engine):
    name = "auto"

    def run(self, graph, program, state, max_rounds=None, stop="quiescent", options=None):
        spark = state.sparkSession
        rounds = max_rounds if max_rounds is not None else ROUNDS
        name, self.reason = choose_engine(state.count(), graph.edges.count(), program, storage_memory(spark) // 2, rounds)
        return ENGINES[name]().run(graph, program, state, max_rounds, stop, options)


ENGINES: dict[str, Callable[[], Engine]] = {e.name: e for e in (Resident, Colocated, ReduceMerge, Reshuffle, Auto)}


def engine_of(engine: str | Engine) -> Engine:
    """By name; 'reshuffle1' is the single-job variant of 'reshuffle'."""
    return engine if isinstance(engine, Engine) else ENGINES[engine.rstrip("12")]()


def options_of(engine: str | Engine, options: EngineOptions | None) -> EngineOptions:
    options = options or EngineOptions()
    return replace(options, jobs=int(engine[-1])) if isinstance(engine, str) and engine[-1] in "12" else options


def count_exchanges(df: DataFrame) -> int:
    """Shuffle exchanges in a frame's physical plan, those behind kept data not counted."""
    text = df._jdf.queryExecution().executedPlan().toString()
    own, depth = 0, None
    for line in text.split("\n"):
        at = len(line) - len(line.lstrip(" :+-*()0123456789"))
        if depth is not None and at > depth:
            continue
        depth = at if "InMemoryTableScan" in line or "InMemoryRelation" in line else None
        own += "Exchange hashpartitioning" in line or "Exchange rangepartitioning" in line or "Exchange SinglePartition" in line
    return own
