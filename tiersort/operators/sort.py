"""The two multi-level sorts: by splitters, and by exact merging.

A virtual PE is a shuffle partition, named by the column ``_ms_pe``. All
groups of a level are handled by the same jobs. Where the input is a table of
files, its PEs are ranges of its rows as they stand there (``_ms_id``, by file
and row), so nothing is moved before the first level; any other input is
written to the shared folder first. A row goes to its target by its key and
its origin alone, so a task that runs again after a lost executor sends every
row to where it went before. Every level but the last is staged in the shared
folder: plans grow by the same few steps with each level.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tiersort.functions.dealing import Dealing, traffic
from tiersort.functions.keys import KeySpec
from tiersort.functions.mixing import PRIME, h
from tiersort.functions.routing import Router, bucket_of, part_of, run_target, target_of
from tiersort.functions.search import Codes, lex_order, same_as_next
from tiersort.operators.layout import SortedLayout
from tiersort.operators.packing import pack, pack_wide
from tiersort.operators.selection import cut_positions, select_keys
from tiersort.operators.splitters import sort_sample
from tiersort.plans.topology import group_range, oversampling, per_level_eps, plan_levels, suggest_ab
from tiersort.sources.sinks import discard, measure_only, scratch, staged

#: Bounds of what the driver holds for a level: pieces or slices, counted cells, keys of a sample, keys sorted in one place.
MOST_SLICES, MOST_CELLS, MOST_SAMPLE, MOST_CENTRAL = 1_000_000, 2_000_000, 4_000_000, 200_000
#: Partitions of one exchange at most; the staged form goes on from there in each group.
MOST_FLAT = 20_000
#: A PE's rows are cut at the borders of so many blocks.
BLOCKS = 64


@dataclass
class Report:
    """What a sort did, level by level and phase by phase."""

    rows: list[dict] = field(default_factory=list)
    kept: list[DataFrame] = field(default_factory=list)

    def add(self, **what) -> None:
        self.rows.append(what)

    def table(self, spark) -> DataFrame:
        """Rows (algorithm, level, phase, metric, value)."""
        out = [(str(r.get("algorithm", "")), int(r.get("level", -1)), str(r.get("phase", "level")), k, float(v)) for r in self.rows for k, v in r.items()
               if k not in ("algorithm", "level", "phase") and isinstance(v, (int, float, np.number))]
        return spark.createDataFrame(out, "algorithm string, level int, phase string, metric string, value double")

    def release(self) -> None:
        """Deletes staged levels; the layout that needs them can't be read any more."""
        for df in self.kept:
            discard(df) if hasattr(df, "_staged_at") else df.unpersist()
        self.kept.clear()


def _plain_scan(df: DataFrame) -> bool:
    """Whether ``df`` only selects and filters the rows of one table of files, by fixed expressions."""
    if any(c.lower() in ("_metadata", "_ms_id") for c in df.columns):
        return False
    node = df._jdf.queryExecution().analyzed()
    if not node.deterministic():
        return False
    while node.nodeName() in ("Project", "Filter", "SubqueryAlias"):
        node = node.children().head()
    return "Relation" in node.nodeName()


def numbered(df: DataFrame, report: Report | None = None) -> tuple[DataFrame, int, int]:
    """``df`` with every row's number in its input (``_ms_id``), the numbers' bound, and the number of rows."""
    try:
        if not _plain_scan(df):
            raise LookupError
        at = df.select(F.col("_metadata.file_path").alias("_f"), F.col("_metadata.row_index").alias("_i"))
    except (AnalysisException, LookupError):
        df = staged(df, "input")
        if report is not None:
            report.kept.append(df)
        at = df.select(F.col("_metadata.file_path").alias("_f"), F.col("_metadata.row_index").alias("_i"))
    files = at.groupBy("_f").agg((F.max("_i") + 1).alias("rows"), F.count("*").alias("n")).orderBy("_f").collect()  # a row for each file
    total = sum(r.rows for r in files)
    if len(files) > 1:
        ahead, table = 0, []
        for r in files:
            table.append((r._f, ahead))
            ahead += r.rows
        out = df.withColumns({"_ms_f": F.col("_metadata.file_path"), "_ms_id": F.col("_metadata.row_index")})
        known = df.sparkSession.createDataFrame(table, "_ms_g string, _ms_a long")
        out = out.join(F.broadcast(known), F.col("_ms_f") == F.col("_ms_g")).withColumn("_ms_id", F.col("_ms_id") + F.col("_ms_a")).drop("_ms_f", "_ms_g", "_ms_a")
    else:
        out = df.withColumn("_ms_id", F.col("_metadata.row_index"))
    return out, total, sum(r.n for r in files)


def placed(p: int, how: str, by: Column, rows: int, seed: int = 0) -> Column:
    """PE by an integer column (nulls as 0): ``hash``, ``cyclic``, ``block`` (equal ranges of values below ``rows``), ``skew`` (nine of ten rows on PE 0)."""
    by = F.pmod(F.coalesce(by.cast("long"), F.lit(0).cast("long")), F.lit(PRIME).cast("long"))
    if how == "hash":
        pe = h(F.pmod(by + seed, F.lit(PRIME).cast("long"))) % p
    elif how == "cyclic":
        pe = by % p
    elif how in ("block", "file"):
        pe = F.least(F.lit(p - 1).cast("long"), F.floor(by * p / F.lit(max(1, rows))))
    elif how == "skew":
        pe = F.when(h(by) % 10 < 9, 0).otherwise(by % p)
    else:
        raise ValueError(how)
    return pe.cast("long")


def place(df: DataFrame, p: int, how: str = "hash", by: str | None = None, seed: int = 0) -> DataFrame:
    """``df`` moved to p PEs (column ``_ms_pe``) by the integer column ``by``, else by a hash of the whole row.

    Null values count as 0. ``file`` and ``input`` place by row numbers in the
    input. The sorts need no such move.
    """
    if how in ("file", "input"):
        rows, total, _ = numbered(df)
        return rows.withColumn("_ms_pe", placed(p, "block", F.col("_ms_id"), total).cast("int")).drop("_ms_id").repartitionById(p, F.col("_ms_pe"))
    by_col = F.col(by).cast("long") if by else F.pmod(F.xxhash64(*df.columns), F.lit(PRIME).cast("long"))
    top = (df.agg(F.max(F.pmod(F.coalesce(by_col, F.lit(0).cast("long")), F.lit(PRIME).cast("long")))).first()[0] or 0) + 1 if how == "block" else 1
    return df.withColumn("_ms_pe", placed(p, how, by_col, top, seed).cast("int")).repartitionById(p, F.col("_ms_pe"))


def _start(df: DataFrame, p: int, placement: str, by: str | None, seed: int, report: Report) -> tuple[DataFrame, int, int, Column | None]:
    """Numbered rows, the numbers' bound, the number of rows, and an expression of the source PE unless it follows from the number."""
    rows, total, n = numbered(df, report)
    if placement in ("input", "file"):
        return rows, total, n, None
    by_col = F.col(by) if by else F.xxhash64(*df.columns)
    top = 1
    if placement == "block":
        top = (rows.agg(F.max(F.pmod(F.coalesce(by_col.cast("long"), F.lit(0).cast("long")), F.lit(PRIME).cast("long")))).first()[0] or 0) + 1
    return rows, total, n, placed(p, placement, by_col, top, seed)


def _sampled(rows: DataFrame, key: KeySpec, codes: Codes, pe: Column, base: np.ndarray, m: int, n: int, seed: int, how: str, p: int) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Owner, flags and values of m rows of each group, drawn by a hash of their origin, in order."""
    share = min(1.0, (m + 5 * m ** 0.5 + 50) * len(base) / max(1, n))
    drawn = F.pmod(F.xxhash64("_ms_id", F.lit(seed)), F.lit(PRIME))
    some = rows.where(drawn < int(PRIME * share) + 1)
    got = some.select(pe.alias("_g"), drawn.alias("_h"), F.col("_ms_id").alias("_i"), *codes.named()).toArrow()  # m rows of each group and some more
    owner = np.searchsorted(base, got.column(0).to_numpy(), "right") - 1
    first = np.lexsort((got.column(2).to_numpy(), got.column(1).to_numpy(), owner))
    place = np.arange(len(first)) - np.searchsorted(owner[first], owner[first])
    took = first[place < m]
    flags, values = codes.read([got.column(i) for i in range(3, got.num_columns)])
    owner, flags, values = owner[took], flags[took], [v[took] for v in values]
    if how == "grid":
        ids = got.column(2).to_numpy()[took]
        known = rows.sparkSession.createDataFrame([(int(i), int(g)) for i, g in zip(ids, owner)], "_ms_t long, _ms_grp int")
        mine = some.join(F.broadcast(known), F.col("_ms_id") == F.col("_ms_t")).select(*key.names, "_ms_id", "_ms_grp")
        ranked = sort_sample(mine, KeySpec(key.cols, key.asc, key.nulls_first, (*key.ties, "_ms_id")), "_ms_grp", "grid", p)
        rank = {r[0]: r[1] for r in ranked.select("_ms_id", "rank").collect()}
        order = np.lexsort((np.array([rank[int(i)] for i in ids], np.int64), owner)) if len(ids) else np.zeros(0, np.int64)
    else:
        arrays, ways = codes.arrays(flags, values)
        order = lex_order([owner, *arrays], [True, *ways])
    return owner[order], flags[order], [v[order] for v in values]


def _splitters(codes: Codes, owner: np.ndarray, flags: np.ndarray, values: list[np.ndarray], groups: int, buckets: int) -> tuple[np.ndarray, int]:
    """Places of the splitters in the sample, and how many key columns tell them from their neighbours."""
    count = np.bincount(owner, minlength=groups)
    ahead = np.cumsum(count) - count
    ranks = -(-np.arange(1, buckets) * count[:, None] // buckets)  # ceil(i * m / buckets)
    at = (ahead[:, None] + ranks - 1)[count > 0].reshape(-1)
    at = at[at >= 0]
    for depth in range(1, len(codes) + 1):
        arrays, _ = codes.arrays(flags, values, depth)
        same = same_as_next([owner, *arrays]) == len(arrays) + 1
        both = np.concatenate([[False], same]) | np.concatenate([same, [False]]) if len(owner) else np.zeros(0, bool)
        if not both[at].any():
            return at, depth
    return at, len(codes)


def splitter_sort(df: DataFrame, key: KeySpec, p: int = 16, k: int | str = 2, by: str | None = None, a: float | str = "paper", b: int = 16, eps: float | None = None,
                  levels: list[int] | None = None, delivery: str = "two_phase", capacity: str = "even", sample_sort: str = "auto", packing: str = "jump",
                  placement: str = "input", ties: str = "level", form: str = "auto", reuse: bool = False, hops: bool = False, seed: int = 0, measure: bool = False,
                  report: Report | None = None) -> SortedLayout:
    """Sorted layout of ``df`` on p PEs by k levels of splitting.

    On every level a sample gives each group b times as many buckets as it has
    parts; counted buckets are packed into parts of least largest load, the
    parts go to groups of PEs, and each group goes on alone. Rows move once a
    level and are put in order at the end only. ``eps`` sets a and b for a
    wanted imbalance.

    ``sample_sort``: ``grid`` ranks the sample on a grid of PEs, ``central`` on
    the driver, ``auto`` there up to MOST_CENTRAL keys. ``ties``: equal keys
    are told apart by their origin, carried through all levels (``origin``) or
    taken anew on each (``level``: where the row stands then), or stay together
    (``none``). ``placement``: which rows a source PE holds, by ``input`` order
    or by the integer column ``by`` (see ``placed``); rows aren't moved for it.
    ``form``: ``flat`` handles all groups of a level in one job, ``staged``
    gives each group of the first level a folder and a sort of its own;
    ``auto`` stages where a level's tables would pass the driver's bounds.
    ``reuse`` takes the splitters known inside of a group over to the next
    level (needs ``ties='origin'``). ``hops`` adds the column ``_ms_hops``: how
    often a row has moved.
    """
    key = key.resolve(df)
    report = Report() if report is None else report
    levels = levels or plan_levels(p, k)
    if math.prod(levels) != p:
        raise ValueError("levels must multiply to p")
    if reuse and ties != "origin":
        raise ValueError("known splitters can be reused with ties='origin' only")
    if eps is not None:
        a, b = suggest_ab(per_level_eps(eps, len(levels)), max(levels))
    columns = list(df.columns)
    rows, total, n, pe = _start(df, p, placement, by, seed, report)
    over = oversampling(n) if a == "paper" else float(a)
    levels = [r for r in levels if r > 1] or [1]
    fits = [math.prod(levels[:i]) * math.ceil(over * b * r) <= MOST_SAMPLE and p * r <= MOST_SLICES for i, r in enumerate(levels)]
    apart = len(levels) > 1 and (form == "staged" or form == "auto" and not all(fits))
    if hops:
        rows = rows.withColumn("_ms_hops", F.lit(0))
        columns.append("_ms_hops")
    spans, loads, known = [(0, p)], np.array([n], np.int64), None
    for level, r in enumerate(levels):
        last = level + 1 == len(levels)
        t = time.time()
        groups, buckets = len(spans), b * r
        base = np.array([x for x, _ in spans], np.int64)
        codes = Codes(rows, key, () if ties == "none" else ("_ms_id",))
        sources = p if level or pe is not None else max(1, min(p, MOST_SLICES // r))
        c = max(1, min(BLOCKS, MOST_CELLS // max(1, sources * buckets), MOST_SLICES // max(1, sources * r)))
        if level == 0 and pe is None:
            block = F.expr(f"cast(_ms_id * {sources * c} div {max(1, total)} as bigint)")
        else:
            of = F.col("_ms_pe").cast("long") if level else pe
            block = of * c + F.pmod(F.xxhash64("_ms_id"), F.lit(c))
        m = math.ceil(over * buckets)
        how = sample_sort if sample_sort != "auto" else "central" if m * groups <= MOST_CENTRAL else "grid"
        owner, flags, values = _sampled(rows, key, codes, F.floor(block / c).cast("long"), base, m, n, seed * 1009 + level, how, p)
        at, depth = _splitters(codes, owner, flags, values, groups, buckets)
        bounds = owner[at], flags[at], [v[at] for v in values]
        if reuse:
            depth = len(codes)
            bounds = bounds if known is None else _with_known(codes, bounds, known, buckets)
        router = Router(codes, depth, *bounds, base.tolist(), c)
        report.add(algorithm="splitter", level=level, phase="splitter selection", seconds=time.time() - t, sample=m, drawn=len(owner), depth=depth)
        t = time.time()
        blocks = sources * c
        cells, sizes = np.zeros((blocks, r), np.int64), np.zeros((groups, buckets), np.int64)
        at_once = blocks * buckets <= MOST_CELLS
        if at_once:
            got = rows.select(block.alias("k"), bucket_of(router, buckets, block).alias("s")).groupBy("k", "s").count().toArrow()  # MOST_CELLS numbers
            k_, s_, n_ = (got.column(i).to_numpy() for i in range(3))
        else:
            got = rows.select(bucket_of(router, buckets, block).alias("s")).groupBy("s").count().toArrow()  # a number for each bucket
            s_, n_ = got.column(0).to_numpy(), got.column(1).to_numpy()
        np.add.at(sizes.reshape(-1), s_, n_)
        part, limits = np.zeros((groups, buckets), np.int32), []
        for g in range(groups):
            limit, parts = pack_wide(df.sparkSession, sizes[g].tolist(), r) if packing == "wide" else pack(sizes[g].tolist(), r, packing)
            part[g] = parts
            limits.append(limit * r / max(1, sizes[g].sum()))
        part = part.reshape(-1)
        if not at_once:
            got = rows.select(block.alias("k"), part_of(router, buckets, part, block).alias("j")).groupBy("k", "j").count().toArrow()  # MOST_SLICES numbers
            k_, j_, n_ = (got.column(i).to_numpy() for i in range(3))
        else:
            j_ = part[s_]
        np.add.at(cells, (k_, j_), n_)
        report.add(algorithm="splitter", level=level, phase="bucket processing", seconds=time.time() - t, limit=max(limits, default=0.0), largest_bucket=float((sizes.max(1) * r / np.maximum(1, sizes.sum(1))).max()))
        t = time.time()
        targets, load, spans = _targets(cells, spans if level else [(0, sources)], [(0, p)] if not level else spans, r, c, delivery, capacity, seed)
        if reuse:
            known = _known(bounds, router, part, buckets, r)
        facts = traffic(np.repeat(np.arange(blocks) // c, r), targets.reshape(-1), cells.reshape(-1))
        sent = rows.withColumn("_ms_to", target_of(router, buckets, part, targets, block))
        if hops:
            sent = sent.withColumn("_ms_hops", F.col("_ms_hops") + 1)
        keep = [*columns, F.col("_ms_to").alias("_ms_pe"), *(["_ms_id"] if ties == "origin" else [])]
        if apart:
            return _groups_apart(sent, columns, spans, key, p, levels, {"a": over, "b": b, "delivery": delivery, "capacity": capacity, "sample_sort": sample_sort, "packing": packing, "ties": ties, "hops": hops, "seed": seed}, report)
        moved = sent.select(*keep).repartitionById(p, F.col("_ms_pe"))
        if not last:
            rows = staged(moved)
            report.kept.append(rows)
            if ties != "origin":
                rows = rows.withColumn("_ms_id", F.col("_ms_pe").cast("long") * (1 << 40) + F.col("_metadata.row_index"))
        loads = load
        report.add(algorithm="splitter", level=level, phase="data delivery", seconds=time.time() - t, groups=r, moves=1, eps=float(load.max(initial=0) * p / n - 1) if n else 0.0, **facts)
    t = time.time()
    if measure:
        measure_only(moved)
        report.rows[-1]["seconds"] += time.time() - t
        t2, alone = time.time(), time.time() - t
    tie = [F.col("_ms_id")] if "_ms_id" in moved.columns else []
    done = moved.sortWithinPartitions("_ms_pe", *key.order(), *tie).drop("_ms_id")
    if measure:
        measure_only(done)
        report.add(algorithm="splitter", level=len(levels), phase="local sort", seconds=max(0.0, time.time() - t2 - alone))
    return SortedLayout(done, key, p, report, loads.tolist())


def _targets(cells: np.ndarray, sources: list[tuple[int, int]], spans: list[tuple[int, int]], r: int, c: int, method: str, capacity: str, seed: int) -> tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]:
    """Target of every (block, part), the PEs' loads, and the parts' PE ranges.

    A piece is cut between blocks: each block's share goes to the PE that has
    its middle place.
    """
    p = spans[-1][0] + spans[-1][1]
    targets, after = np.zeros(cells.shape, np.int32), []
    for (first, s), (base, q) in zip(sources, spans):
        parts = [group_range(base, q, r, j) for j in range(r)]
        after += parts
        mine = cells[first * c:(first + s) * c].reshape(s, c, r)
        dealing = Dealing(mine.sum(1), [x for x, _ in parts], [y for _, y in parts], method, capacity, seed, np.arange(first, first + s))
        middle = np.cumsum(mine, 1) - mine + np.maximum(0, mine - 1) // 2
        src, grp = np.broadcast_to(np.arange(s)[:, None, None], mine.shape), np.broadcast_to(np.arange(r), mine.shape)
        full = mine > 0
        out = np.broadcast_to(np.array([x for x, _ in parts], np.int32), mine.shape).copy()
        out[full] = dealing.at(src[full], grp[full], middle[full])
        targets[first * c:(first + s) * c] = out.reshape(s * c, r)
    load = np.zeros(p, np.int64)
    np.add.at(load, targets.reshape(-1), cells.reshape(-1))
    return targets, load, after


def _known(bounds: tuple, router: Router, part: np.ndarray, buckets: int, r: int) -> tuple:
    """Those bounds that lie inside of a part: the part's number among all, flags, values."""
    owner, flags, values = bounds
    at = owner * buckets + np.arange(len(owner)) - router.first[owner]
    inside = np.flatnonzero(part[at] == part[np.minimum(at + 1, len(part) - 1)])
    return (owner * r + part[at])[inside], flags[inside], [v[inside] for v in values]


def _with_known(codes: Codes, bounds: tuple, known: tuple, buckets: int) -> tuple:
    """Known bounds and, as far as there is room, fresh ones."""
    owner, flags, values = (np.concatenate([a, b]) if isinstance(a, np.ndarray) else [np.concatenate(x) for x in zip(a, b)] for a, b in zip(known, bounds))
    fresh, keep = np.arange(len(owner)) >= len(known[0]), []
    for g in np.unique(owner):
        old, new = np.flatnonzero((owner == g) & ~fresh)[:buckets - 1], np.flatnonzero((owner == g) & fresh)
        room = buckets - 1 - len(old)
        keep += [old, new[np.unique(np.linspace(0, len(new) - 1, min(room, len(new))).astype(int))] if room and len(new) else new[:0]]
    which = np.concatenate(keep) if keep else np.zeros(0, np.int64)
    arrays, ways = codes.arrays(flags[which], [v[which] for v in values])
    which = which[lex_order([owner[which], *arrays], [True, *ways])]
    return owner[which], flags[which], [v[which] for v in values]


def _groups_apart(sent: DataFrame, columns: list[str], spans: list[tuple[int, int]], key: KeySpec, p: int, levels: list[int], options: dict, report: Report) -> SortedLayout:
    """The staged form: each group of the first level becomes a folder, which is sorted by itself."""
    spark, r, parts = sent.sparkSession, len(spans), min(p, MOST_FLAT)
    path = scratch(spark, "groups")
    grp = F.expr(f"cast((((_ms_to + 1L) * {r} - 1) div {p}) * {p} div {r} as int)")  # its first PE
    (sent.select(*columns, grp.alias("_ms_grp"), F.expr(f"cast(_ms_to * {parts}L div {p} as int)").alias("_ms_part")).repartitionById(parts, F.col("_ms_part"))
     .drop("_ms_part").write.partitionBy("_ms_grp").parquet(path))
    whole = spark.read.parquet(path)
    out, loads = None, []
    for base, q in spans:
        try:
            mine = spark.read.schema(whole.drop("_ms_grp").schema).parquet(f"{path}/_ms_grp={base}")
        except AnalysisException:  # a group without rows
            loads += [0] * q
            continue
        names = [c for c in columns if c != "_ms_hops"]
        part = splitter_sort(mine.select(*names), key, q, levels=levels[1:], **{**options, "hops": False}, report=report) if q > 1 else None
        if part is None:
            n = mine.count()
            df, load = mine.select(*names).withColumn("_ms_pe", F.lit(0)).repartitionById(1, F.col("_ms_pe")).sortWithinPartitions("_ms_pe", *key.order()), [n]
        else:
            df, load = part.df, part.loads
        df = df.withColumn("_ms_pe", F.col("_ms_pe") + F.lit(base))
        if options["hops"]:
            df = df.withColumn("_ms_hops", F.lit(len(levels)))
        out = df if out is None else out.unionByName(df)
        loads += load
    if out is None:
        out = whole.drop("_ms_grp").withColumn("_ms_pe", F.lit(0))
    return SortedLayout(out, key, p, report, loads)


def sorted_runs(df: DataFrame, key: KeySpec, p: int, placement: str = "input", by: str | None = None, seed: int = 0, report: Report | None = None) -> tuple[DataFrame, int]:
    """``df`` as staged sorted runs (run ``_ms_pe``, position ``_ms_pos``) and the number of its rows.

    The partitions of the input are sorted as they are. Only where it has
    fewer of them than p, or a placement is wanted, rows are first dealt to p
    PEs. Run numbers and positions are fixed by being written.
    """
    report = Report() if report is None else report
    rows, total, n, pe = _start(df, p, placement, by, seed, report)
    if pe is None and rows._jdf.queryExecution().toRdd().getNumPartitions() < p:
        pe = F.expr(f"cast(_ms_id * {p} div {max(1, total)} as bigint)")
    if pe is not None:
        rows = rows.withColumn("_ms_pe", pe.cast("int")).repartitionById(p, F.col("_ms_pe"))
    rows = rows.sortWithinPartitions(*key.order(), "_ms_id").drop("_ms_id")
    out = staged(numbered_runs(rows), "runs")
    report.kept.append(out)
    return out, n


def numbered_runs(rows: DataFrame) -> DataFrame:
    """Rows with their partition as run and their place in it; to be written at once."""
    return rows.withColumns({"_ms_pe": F.spark_partition_id(), "_ms_pos": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))})


def merge_sort(df: DataFrame, key: KeySpec, p: int = 16, k: int | str = 2, by: str | None = None, levels: list[int] | None = None, delivery: str = "two_phase", capacity: str = "even",
               merge: str = "arrow", fan_in: int = 64, pivots_per_round: int = 32, placement: str = "input", seed: int = 0, measure: bool = False) -> SortedLayout:
    """Sorted layout of ``df`` on p PEs, sizes equal up to rounding, by k levels of exact splitting and merging.

    On every level each group's runs are cut at the exact ranks between its
    parts, pieces are delivered, and what a PE receives is merged into its new
    run: by an explicit merge of Arrow batches (``arrow``, at most ``fan_in``
    runs at once), by Spark's sort (``timsort``), or by a sort over all columns
    that knows nothing of runs (``resort``, the slow competitor's way). Keys may
    repeat: a cut tells equal ones apart by where they stand on that level.
    """
    key = key.resolve(df)
    report = Report()
    levels = levels or plan_levels(p, k)
    if math.prod(levels) != p:
        raise ValueError("levels must multiply to p")
    t = time.time()
    runs, n = sorted_runs(df, key, p, placement, by, seed, report)
    report.add(algorithm="merge", level=-1, phase="local sort", seconds=time.time() - t)
    return merge_levels(runs, key, p, [r for r in levels if r > 1] or [1], delivery, capacity, merge, fan_in, pivots_per_round, seed, measure, report)


def merge_levels(runs: DataFrame, key: KeySpec, p: int, levels: list[int], delivery: str = "two_phase", capacity: str = "even", merge: str = "arrow", fan_in: int = 64,
                 pivots_per_round: int = 32, seed: int = 0, measure: bool = False, report: Report | None = None) -> SortedLayout:
    """Layout of sorted runs (columns ``_ms_pe`` and ``_ms_pos``) on p PEs; on the first level their number may be any."""
    from tiersort.operators.merging import merge_partitions

    if merge not in ("arrow", "timsort", "resort"):
        raise ValueError(merge)
    report = Report() if report is None else report
    rows, spans, block = runs, [(0, p)], F.col("_ms_pe").cast("long")
    columns = [c for c in runs.columns if c not in ("_ms_pe", "_ms_pos", "_ms_src")]
    total = None
    for level, r in enumerate(levels):
        last, t = level + 1 == len(levels), time.time()
        lengths = dict(rows.groupBy("_ms_pe").count().collect())  # a row for each run
        names = np.array(sorted(lengths), np.int64)
        total = sum(lengths.values()) if total is None else total
        base = [x for x, _ in spans] if level else [0]
        parent = np.searchsorted(base, names, "right") - 1
        sizes = {g: sum(lengths[e] for e in names[parent == g].tolist()) for g in range(len(spans))}
        # the rank where a part begins follows from the whole order, so sizes differ by one at most in the end
        plan = [[group_range(x, q, r, j) for j in range(r)] for x, q in spans]
        wanted = {g: [total * x // p - total * spans[g][0] // p for x, _ in plan[g][1:]] for g in range(len(spans))}
        stats: dict = {}
        keys, cuts = select_keys(rows, key, {g: sorted(set(ks)) for g, ks in wanted.items()}, sizes, block, ("_ms_pe", "_ms_pos"), base, "_ms_pos", pivots_per_round, seed + 1, stats=stats)
        found = cut_positions(rows, key, keys, cuts, block, "_ms_pos", base)
        if len(names) * r > MOST_SLICES:
            raise ValueError(f"{len(names)} runs cut into {r} parts; the driver holds {MOST_SLICES} pieces")
        starts, local = np.zeros((len(names), r), np.int64), np.zeros(len(names), np.int64)
        dealings, pieces = [], np.zeros((len(names), r), np.int64)
        for g in range(len(spans)):
            mine = np.flatnonzero(parent == g)
            local[mine] = np.arange(len(mine))
            for j, want in enumerate(wanted[g], 1):
                starts[mine, j] = [lengths[e] if want >= sizes[g] else found[g, want].get(e, 0) for e in names[mine].tolist()]
            ends = np.concatenate([starts[mine, 1:], np.array([[lengths[e]] for e in names[mine].tolist()], np.int64).reshape(-1, 1)], 1)
            pieces[mine] = ends - starts[mine]
            dealings.append(Dealing(pieces[mine], [x for x, _ in plan[g]], [q for _, q in plan[g]], delivery, capacity, seed, names[mine]))
        report.add(algorithm="merge", level=level, phase="splitter selection", seconds=time.time() - t, rounds=stats.get("rounds", 0), ranks=stats.get("ranks", 0), rows_read=sum(stats.get("rows_read", [])))
        t = time.time()
        sent = rows.select(*columns, F.col("_ms_pe").alias("_ms_src"), run_target(names, starts, parent, local, dealings, F.col("_ms_pe"), F.col("_ms_pos")).alias("_ms_pe"))
        moved = sent.repartitionById(p, F.col("_ms_pe"))
        merged = merge_partitions(moved, key, fan_in, merge == "resort") if merge != "timsort" else moved.drop("_ms_src").sortWithinPartitions("_ms_pe", *key.order())
        if not last:
            rows = staged(merged if merge != "timsort" else merged.withColumn("_ms_pos", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))), "merged")
            report.kept.append(rows)
        elif measure:
            measure_only(moved)
        spans = [x for parts in plan for x in parts]
        report.add(algorithm="merge", level=level, phase="data delivery", seconds=time.time() - t, groups=r, moves=1, **_run_traffic(names, pieces, dealings, parent, local))
    if measure:
        t = time.time()
        measure_only(merged)
        report.add(algorithm="merge", level=len(levels), phase="bucket processing", seconds=max(0.0, time.time() - t - report.rows[-1]["seconds"]))
    loads = [total * (x + 1) // p - total * x // p for x in range(p)]
    return SortedLayout(merged.withColumnRenamed("_ms_pos", "_ms_row") if merge != "timsort" else merged, key, p, report, loads)


def _run_traffic(names: np.ndarray, pieces: np.ndarray, dealings: list, parent: np.ndarray, local: np.ndarray, most: int = 200_000) -> dict[str, float]:
    """Messages of a level's pieces, from the targets of their first, last and evenly spread places."""
    src, target, words = [], [], []
    for e, j in zip(*np.nonzero(pieces)):
        if len(src) >= most:
            break
        d, n = dealings[parent[e]], int(pieces[e, j])
        x = np.unique(np.linspace(0, n - 1, min(n, 4 * int(d.q[j]) + 2)).astype(np.int64))
        t = d.at(np.full(len(x), local[e]), np.full(len(x), j), x)
        hit, count = np.unique(t, return_counts=True)
        src += [int(names[e])] * len(hit)
        target += hit.tolist()
        words += (count * n / count.sum()).tolist()
    return traffic(np.array(src, np.int64), np.array(target, np.int64), np.array(words, float)) if src else {}
