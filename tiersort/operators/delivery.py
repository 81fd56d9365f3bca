"""Delivery of pieces: which PE of its destination group gets which part of a piece.

A piece is what one source PE holds for one destination group. All methods
work on the table of piece sizes alone (one row for each PE and group) and
return slices (grp, pe, from_pos, to_pos, target): positions [from_pos, to_pos)
of the piece go to PE ``target``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tiersort.functions.mixing import mix_pair

SLICE = ["grp", "pe", "from_pos", "to_pos", "target"]


def _scan(partition: list[str], order: list[Column | str], what: Column) -> Column:
    """Exclusive prefix sum."""
    return F.coalesce(F.sum(what).over(Window.partitionBy(*partition).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("long")


def sized(pieces: DataFrame, capacity: str = "even") -> DataFrame:
    """Pieces with their group's total ``m``, its PEs (``base``, ``q``) and the capacity ``cap`` of one of them.

    ``pieces`` has (pe, grp, size, base, q). ``even``: a group's total is
    spread over its own PEs. ``bound``: every PE may take as much as the
    fullest group's PEs must, so lighter groups cut their pieces less.
    """
    rows = pieces.withColumn("m", F.sum("size").over(Window.partitionBy("grp"))).where("size > 0")
    cap = F.ceil(F.col("m") / F.col("q")).cast("long")
    if capacity == "bound":
        most = pieces.groupBy("grp").agg(F.sum("size").alias("m"), F.first("q").alias("q")).agg(F.max(F.ceil(F.col("m") / F.col("q"))).cast("long").alias("cap"))
        return rows.crossJoin(F.broadcast(most))  # one row
    return rows.withColumn("cap", cap)


def _cut(runs: DataFrame, capacity: str) -> DataFrame:
    """Slices of runs (grp, pe, size, lead, start, m, q, base, cap): ``start`` is the run's place in the group, ``lead`` in its piece."""
    if capacity == "bound":
        first, last = F.expr("start div cap"), F.expr("(start + size - 1) div cap")
        low, high = F.expr("t * cap"), F.expr("(t + 1) * cap")
    else:  # position x of m goes to floor(x * q / m): PE t holds [ceil(t*m/q), ceil((t+1)*m/q))
        first, last = F.expr("start * q div m"), F.expr("(start + size - 1) * q div m")
        low, high = F.expr("(t * m + q - 1) div q"), F.expr("((t + 1) * m + q - 1) div q")
    out = runs.withColumn("t", F.explode(F.sequence(first.cast("long"), last.cast("long")))).withColumn("lo", low).withColumn("hi", high)
    return out.select(F.col("grp"), F.col("pe"), (F.greatest("lo", "start") - F.col("start") + F.col("lead")).cast("long").alias("from_pos"),
                      (F.least(F.col("hi"), F.col("start") + F.col("size")) - F.col("start") + F.col("lead")).cast("long").alias("to_pos"),
                      (F.col("base") + F.col("t")).cast("int").alias("target")).where("to_pos > from_pos")


def deliver(pieces: DataFrame, method: str = "two_phase", capacity: str = "even", seed: int = 1, pes: int | None = None, merge: str = "window") -> DataFrame:
    """Slices of ``pieces`` (pe, grp, size, base, q).

    ``prefix`` counts a group's elements in the order of source PEs and cuts
    the count evenly. ``permuted`` does so in a pseudo-random order of the PEs,
    another one for each group. ``chunked`` first cuts pieces into chunks of
    less than 1/(2r) of a PE's load and permutes these. ``two_phase`` gives
    small pieces away whole and fills the PEs up with the large ones.
    """
    rows = sized(pieces, capacity)
    if method == "two_phase":
        return _two_phase(pieces, pes, merge)
    if method in ("prefix", "permuted"):
        order = ["pe"] if method == "prefix" else [mix_pair(F.col("pe"), F.col("grp"), seed), "pe"]
        return _cut(rows.withColumn("start", _scan(["grp"], order, F.col("size"))).withColumn("lead", F.lit(0).cast("long")), capacity)
    if method == "chunked":
        chunk = F.greatest(F.lit(1), F.expr("cap div (2 * q)"))  # a PE's load over twice the number of PEs that may send
        cut = rows.withColumn("chunk", chunk).withColumn("c", F.explode(F.sequence(F.lit(0).cast("long"), F.expr("(size - 1) div chunk"))))
        cut = cut.withColumn("lead", F.col("c") * F.col("chunk")).withColumn("size", F.least(F.col("chunk"), F.col("size") - F.col("lead")))
        cut = cut.withColumn("start", _scan(["grp"], [mix_pair(F.col("pe") * 4096 + F.col("c"), F.col("grp"), seed), "pe", "c"], F.col("size")))
        return coalesced(_cut(cut, capacity))
    raise ValueError(method)


def coalesced(slices: DataFrame) -> DataFrame:
    """Neighbouring slices of a piece with the same target become one."""
    order = Window.partitionBy("grp", "pe", "target").orderBy("from_pos")
    fresh = (F.coalesce(F.lag("to_pos").over(order), F.lit(-1)) != F.col("from_pos")).cast("int")
    run = F.sum("fresh").over(order)
    return slices.withColumn("fresh", fresh).withColumn("run", run).groupBy("grp", "pe", "target", "run").agg(
        F.min("from_pos").alias("from_pos"), F.max("to_pos").alias("to_pos")).select(*SLICE)


def _two_phase(pieces: DataFrame, pes: int | None, merge: str = "window") -> DataFrame:
    """Small pieces (at most n / (2 p r)) whole by number, large ones into what room is left.

    A group's small pieces are numbered in PE order and dealt evenly to its
    PEs, which they fill by half at most. Prefix sums of the room left (by PE)
    and of the large pieces (by source) are then overlapped as intervals. The
    capacity is that of the fullest group, so there is room for everything.
    ``merge``: overlaps by one merging pass (``window``) or a range join.
    """
    rows = sized(pieces, "bound")
    facts = rows.groupBy().agg(F.sum("size").alias("n"))
    of = pieces.agg((F.max("pe") + 1 if pes is None else F.lit(pes)).cast("long").alias("p"), F.countDistinct("grp").alias("r"))
    rows = rows.crossJoin(F.broadcast(facts)).crossJoin(F.broadcast(of))  # one row each
    rows = rows.withColumn("small", F.col("size") * 2 * F.col("p") * F.col("r") <= F.col("n"))
    number = F.count("*").over(Window.partitionBy("grp").orderBy("pe").rowsBetween(Window.unboundedPreceding, -1))
    small = rows.where("small").withColumn("t", F.least(F.col("q") - 1, F.floor(number * F.col("q") / F.col("p"))).cast("long"))
    given = small.groupBy("grp", "t").agg(F.sum("size").alias("given"))
    groups = pieces.groupBy("grp").agg(F.first("base").alias("base"), F.first("q").alias("q"))
    cap = rows.agg(F.max("cap").alias("cap"))
    room = (groups.crossJoin(F.broadcast(cap)).withColumn("t", F.explode(F.sequence(F.lit(0).cast("long"), F.col("q").cast("long") - 1)))
            .join(given, ["grp", "t"], "left").withColumn("free", F.col("cap") - F.coalesce("given", F.lit(0))))
    room = room.withColumn("x", _scan(["grp"], ["t"], F.col("free"))).where("free > 0").select("grp", F.col("t").alias("rt"), "x", "free")
    large = rows.where("not small").withColumn("y", _scan(["grp"], ["pe"], F.col("size")))
    met = _met_by_window(large, room) if merge == "window" else _met_by_range(large, room)
    big = met.select("grp", "pe", (F.greatest("x", "y") - F.col("y")).cast("long").alias("from_pos"),
                     (F.least(F.col("x") + F.col("free"), F.col("y") + F.col("size")) - F.col("y")).cast("long").alias("to_pos"), (F.col("base") + F.col("rt")).cast("int").alias("target"))
    whole = small.select("grp", "pe", F.lit(0).cast("long").alias("from_pos"), F.col("size").alias("to_pos"), (F.col("base") + F.col("t")).cast("int").alias("target"))
    return whole.unionByName(big.where("to_pos > from_pos"))


def _met_by_range(large: DataFrame, room: DataFrame) -> DataFrame:
    """Large pieces with the rooms they overlap, as a range join within each group."""
    met = large.join(room, (large["grp"] == room["grp"]) & (F.col("x") < F.col("y") + F.col("size")) & (F.col("y") < F.col("x") + F.col("free")))
    return met.drop(room["grp"])


def _met_by_window(large: DataFrame, room: DataFrame) -> DataFrame:
    """As the range join, by merging both prefix sums: one ordered pass gives each piece the rooms of its first and last element."""
    ends = large.select("grp", "pe", F.col("y").alias("v"), F.lit(1).alias("end")).unionByName(large.select("grp", "pe", (F.col("y") + F.col("size") - 1).alias("v"), F.lit(2).alias("end")))
    events = room.select("grp", F.lit(None).cast("int").alias("pe"), F.col("x").alias("v"), F.lit(0).alias("end"), "rt").unionByName(ends, allowMissingColumns=True)
    order = Window.partitionBy("grp").orderBy("v", "end", "rt").rowsBetween(Window.unboundedPreceding, 0)  # rooms before pieces at one place
    found = events.withColumn("at", F.last("rt", True).over(order)).where("end > 0").groupBy("grp", "pe").agg(F.min("at").alias("first"), F.max("at").alias("last"))
    spread = large.join(found, ["grp", "pe"]).withColumn("rt", F.explode(F.sequence("first", "last"))).drop("first", "last")
    return spread.join(room, ["grp", "rt"])


def route_descriptors(pieces: DataFrame, r: int) -> DataFrame:
    """Descriptors of large pieces at the PE of the destination group that sorts them out: r neighbouring sources meet at one."""
    return pieces.select("grp", "pe", "size", (F.col("base") + F.expr(f"pe div {r}") % F.col("q")).cast("int").alias("at"))


def message_stats(slices: DataFrame, exchange: str = "one_factor", p: int | None = None) -> DataFrame:
    """One row: messages and words, most and mean, sent and received by a PE, and the messages of all.

    ``one_factor`` leaves empty messages out; the ``dense`` exchange of ``p``
    PEs sends every pair one, with words or without.
    """
    sent = slices.groupBy("pe").agg(F.countDistinct("target").alias("n"), F.sum(F.col("to_pos") - F.col("from_pos")).alias("w"))
    got = slices.groupBy("target").agg(F.countDistinct("pe").alias("n"), F.sum(F.col("to_pos") - F.col("from_pos")).alias("w"))
    a = sent.agg(F.max("n").alias("max_sent"), F.avg("n").alias("mean_sent"), F.max("w").alias("words_sent"), F.sum("n").alias("messages"))
    b = got.agg(F.max("n").alias("max_recv"), F.avg("n").alias("mean_recv"), F.max("w").alias("words_recv"))
    out = a.crossJoin(b).withColumn("bottleneck", F.greatest("words_sent", "words_recv"))  # one row each
    if exchange == "dense":
        each = F.lit(p - 1).cast("long")
        out = out.withColumns({"max_sent": each, "max_recv": each, "mean_sent": each.cast("double"), "mean_recv": each.cast("double"), "messages": F.lit(p * (p - 1)).cast("long")})
    return out


def cross_volume(slices: DataFrame, island: int) -> DataFrame:
    """Rows (grp, words, crossing): words by group, and those that leave their island of ``island`` PEs."""
    words = F.col("to_pos") - F.col("from_pos")
    leaves = F.expr(f"pe div {island} <> target div {island}")
    return slices.groupBy("grp").agg(F.sum(words).alias("words"), F.sum(F.when(leaves, words).otherwise(0)).alias("crossing"))


def gossip_schedule(spark: SparkSession, p: int, words: int = 1, how: str = "hypercube", held: DataFrame | None = None) -> DataFrame:
    """Rows (round, src, dst, words) by which all of p PEs come to hold what each of them has.

    ``hypercube`` (p a power of two): partners differ in one bit and exchange
    all they hold, which is merged. ``tree`` (any p): gathered along a binary
    tree to PE 0, then everything is sent down again. A PE has ``words``, or
    what rows (pe, words) of ``held`` say (not listed: none).
    """
    bits = max(0, p - 1).bit_length()
    if how == "hypercube" and p != 1 << bits:
        raise ValueError("a hypercube has a power of two of PEs")
    pes = spark.range(p).select(F.col("id").cast("int").alias("pe"))
    own = pes.withColumn("words", F.lit(words).cast("long")) if held is None else pes.join(held.select("pe", "words"), "pe", "left").select("pe", F.coalesce("words", F.lit(0)).cast("long").alias("words"))
    # before a round, a PE has the words of the PEs that differ from it in lower bits only
    turns = F.explode(F.sequence(F.lit(0), F.lit(bits - 1))) if bits else F.explode(F.array().cast("array<int>"))
    right = lambda x: F.call_function("shiftright", F.col(x), F.col("round"))
    block = own.select("words", "pe", turns.alias("round")).groupBy("round", right("pe").alias("block")).agg(F.sum("words").alias("words"))
    step = F.call_function("shiftleft", F.lit(1), F.col("round"))
    cell = pes.select(F.col("pe").alias("src"), turns.alias("round")).withColumn("block", right("src"))
    if how == "hypercube":
        return cell.join(block, ["round", "block"]).select("round", "src", F.col("src").bitwiseXOR(step).alias("dst"), "words")
    up = cell.where(F.col("src") % (step * 2) == step).join(block, ["round", "block"]).select("round", "src", (F.col("src") - step).alias("dst"), "words")
    total = own.agg(F.sum("words").alias("words"))
    down = up.drop("words").crossJoin(F.broadcast(total)).select((F.lit(2 * bits - 1) - F.col("round")).alias("round"), F.col("dst").alias("src"), F.col("src").alias("dst"), "words")  # one row
    return up.unionByName(down)


def one_factor_schedule(messages: DataFrame, p: int, skip_empty: bool = True) -> DataFrame:
    """Rows (round, src, dst, words): in round t PE i is paired with (t - i) mod p; rounds without words are left out."""
    out = messages.where("src <> dst").select(((F.col("src") + F.col("dst")) % p).cast("int").alias("round"), "src", "dst", "words")
    return out.where("words > 0") if skip_empty else out


def edge_colour_schedule(messages: list[tuple[int, int, int]]) -> list[tuple[int, int, int, int]]:
    """Rows (round, src, dst, words) that split messages so that the rounds' lengths sum to the largest load of a PE.

    For study on the driver: in each round a matching that covers every PE of
    the largest remaining load, for as long as it stays valid.
    """
    left = {(s, d): w for s, d, w in messages if w > 0 and s != d}
    out, turn = [], 0
    while left:
        load: dict[tuple[str, int], int] = {}
        for (s, d), w in left.items():
            load["s", s] = load.get(("s", s), 0) + w
            load["d", d] = load.get(("d", d), 0) + w
        top = max(load.values())
        tight = [x for x, w in load.items() if w == top]
        match: dict[tuple[str, int], tuple[str, int]] = {}

        def grow(x: tuple[str, int], seen: set, match=match, left=left) -> bool:
            side = x[0]
            for (s, d) in sorted(left, key=lambda e: -left[e]):
                y = ("d", d) if side == "s" else ("s", s)
                if (("s", s) if side == "s" else ("d", d)) == x and y not in seen:
                    seen.add(y)
                    if y not in match or grow(match[y], seen):
                        match[x], match[y] = y, x
                        return True
            return False

        for x in tight:
            if x not in match:
                grow(x, set())
        pairs = [(x[1], y[1]) for x, y in match.items() if x[0] == "s" and match.get(y) == x and (x[1], y[1]) in left]
        covered = {("s", s) for s, _ in pairs} | {("d", d) for _, d in pairs}
        span = min([left[e] for e in pairs] + [top - w for x, w in load.items() if x not in covered and top > w])
        for e in pairs:
            out.append((turn, *e, span))
            left[e] -= span
            if not left[e]:
                del left[e]
        turn += 1
    return out
