"""A sorted, range-partitioned table and what it makes cheap.

``SortedLayout`` holds rows on p PEs (column ``_ms_pe``), each PE sorted and
no PE after the next. Window functions over the whole order run inside the PEs
and add what the PEs before hold (a carry from one small row for each PE), so
no task sees the whole table.
"""

from __future__ import annotations

from functools import cached_property
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType, NumericType

from tiersort.functions.keys import KeySpec
from tiersort.functions.routing import reached
from tiersort.functions.search import Codes


class SortedLayout:
    """``df`` has the column ``_ms_pe``; ``_ms_row`` (place in the PE) may be there, and ``loads`` (rows of each PE) be known."""

    def __init__(self, df: DataFrame, key: KeySpec, p: int, report=None, loads: list[int] | None = None):
        self.df, self.key, self.p, self.report, self.loads = df, key, p, report, loads

    @property
    def columns(self) -> list[str]:
        return [c for c in self.df.columns if c not in ("_ms_pe", "_ms_row")]

    @cached_property
    def offsets(self) -> DataFrame:
        """Rows (pe, cnt, offset), one for each PE that has rows; without a job where loads are known."""
        if self.loads is None:
            return self.stats.select("pe", "cnt", "offset")
        ahead = [0, *accumulate(self.loads)]
        return self.df.sparkSession.createDataFrame([(x, n, ahead[x]) for x, n in enumerate(self.loads) if n], "pe int, cnt long, offset long")

    def _numbered(self) -> DataFrame:
        """Rows with their place in the PE (``_ms_n``, from 1)."""
        if "_ms_row" in self.df.columns:
            return self.df.withColumn("_ms_n", F.col("_ms_row") + 1).drop("_ms_row")
        return self.df.withColumn("_ms_n", F.row_number().over(self._local()).cast("long"))

    @cached_property
    def stats(self) -> DataFrame:
        """Rows (pe, cnt, offset, first_key, last_key), one for each PE that has rows; p rows at most."""
        k = self.key.struct()
        local = self._numbered().groupBy(F.col("_ms_pe").alias("pe")).agg(
            F.count("*").alias("cnt"), F.min_by(k, "_ms_n").alias("first_key"), F.max_by(k, "_ms_n").alias("last_key"))
        ahead = Window.orderBy("pe").rowsBetween(Window.unboundedPreceding, -1)  # p rows
        out = local.withColumn("offset", F.coalesce(F.sum("cnt").over(ahead), F.lit(0)).cast("long"))
        return out.select("pe", "cnt", "offset", "first_key", "last_key").persist()

    def _plain(self) -> DataFrame:
        return self.df.drop("_ms_row")

    def _local(self):
        return Window.partitionBy("_ms_pe").orderBy(*self.key.order())

    def _carry(self, df: DataFrame, table: DataFrame) -> DataFrame:
        """Join with a table of one row for each PE (column ``pe``): p rows, broadcast."""
        return df.join(F.broadcast(table), F.col("_ms_pe") == F.col("pe")).drop("pe")

    def with_rank(self, name: str = "rank", start: int = 0) -> DataFrame:
        """Rows with their position in the whole order."""
        out = self._carry(self._numbered(), self.offsets.select("pe", "offset"))
        return out.withColumn(name, F.col("offset") + F.col("_ms_n") - 1 + start).drop("_ms_n", "offset")

    def load_stats(self) -> DataFrame:
        """One row: largest and mean load, and the imbalance max * p / n - 1."""
        return self.offsets.agg(F.max("cnt").alias("max_load"), (F.sum("cnt") / self.p).alias("mean_load"), (F.max("cnt") * self.p / F.sum("cnt") - 1).alias("eps"))

    # ---- windows over the whole order

    def rank_window(self, of: KeySpec | None = None) -> DataFrame:
        """Rows with row_number, rank, dense_rank, percent_rank and cume_dist by the key without its ties."""
        by = of or self.key.without_ties()
        same = F.struct(*by.names)
        rows = self.with_rank("row_number", 1).withColumn("_ms_v", same)
        run = Window.partitionBy("_ms_pe", "_ms_v")
        rows = rows.withColumn("_ms_first", F.min("row_number").over(run)).withColumn("_ms_last", F.max("row_number").over(run))
        rows = rows.withColumn("_ms_d", F.dense_rank().over(Window.partitionBy("_ms_pe").orderBy(*by.order())))
        # one row for each PE: its border runs and the number of distinct keys
        border = rows.groupBy(F.col("_ms_pe").alias("pe")).agg(
            F.min_by("_ms_v", "row_number").alias("head"), F.max_by("_ms_v", "row_number").alias("tail"), F.max("_ms_d").alias("d"),
            F.min("_ms_first").alias("start"), F.max("_ms_last").alias("stop"), F.max("_ms_first").alias("tail_first"), F.min("_ms_last").alias("head_last"))
        w = Window.orderBy("pe")  # p rows
        joins = F.coalesce(F.lag("tail").over(w).eqNullSafe(F.col("head")) & F.lag("pe").over(w).isNotNull(), F.lit(False)).cast("int")
        border = border.withColumn("joins", joins).withColumn("dbase", F.coalesce(F.sum("d").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) - F.sum("joins").over(w))
        # groups of PEs chained by one run: where the run at the head began, and where that at the tail ends
        border = border.withColumn("own", F.when((F.col("joins") == 0) | (F.col("d") > 1), F.col("tail_first")))
        border = border.withColumn("head_from", F.when(F.col("joins") == 1, F.last("own", True).over(w.rowsBetween(Window.unboundedPreceding, -1))).otherwise(F.col("start")))
        nxt = F.coalesce(F.lead("joins").over(w), F.lit(0))
        border = border.withColumn("goes", nxt).withColumn("end", F.when((F.col("d") > 1) | (nxt == 0), F.col("head_last")))
        border = border.withColumn("tail_to", F.when(F.col("goes") == 1, F.first("end", True).over(w.rowsBetween(1, Window.unboundedFollowing))).otherwise(F.col("stop")))
        out = self._carry(rows, border.select("pe", "head", "tail", "head_from", "tail_to", "dbase"))
        total = self.offsets.agg(F.sum("cnt").alias("_ms_total"))
        out = out.crossJoin(F.broadcast(total))  # one row
        first = F.when(F.col("_ms_v").eqNullSafe(F.col("head")), F.col("head_from")).otherwise(F.col("_ms_first"))
        last = F.when(F.col("_ms_v").eqNullSafe(F.col("tail")), F.col("tail_to")).otherwise(F.col("_ms_last"))
        return out.withColumns({
            "rank": first, "dense_rank": (F.col("dbase") + F.col("_ms_d")).cast("long"),
            "percent_rank": F.when(F.col("_ms_total") > 1, (first - 1) / (F.col("_ms_total") - 1)).otherwise(F.lit(0.0)), "cume_dist": last / F.col("_ms_total"),
        }).drop("_ms_v", "_ms_first", "_ms_last", "_ms_d", "head", "tail", "head_from", "tail_to", "dbase", "_ms_total")

    def ntile(self, tiles: int, name: str = "ntile") -> DataFrame:
        rows = self.with_rank("_ms_r").crossJoin(F.broadcast(self.offsets.agg(F.sum("cnt").alias("_ms_total"))))  # one row
        size, extra = F.expr(f"_ms_total div {tiles}"), F.expr(f"_ms_total % {tiles}")
        big = extra * (size + 1)
        tile = F.when(F.col("_ms_r") < big, F.floor(F.try_divide(F.col("_ms_r"), size + 1))).otherwise(extra + F.floor(F.try_divide(F.col("_ms_r") - big, size)))
        return rows.withColumn(name, (tile + 1).cast("int")).drop("_ms_r", "_ms_total")

    def running(self, value: Column, how: str = "sum", name: str = "running") -> DataFrame:
        """Rows with the aggregate of ``value`` from the first row of the order to this one."""
        rows = self._plain().withColumn("_ms_x", value)
        agg = {"sum": F.sum, "min": F.min, "max": F.max, "count": F.count}[how]
        parts = rows.groupBy(F.col("_ms_pe").alias("pe")).agg(agg("_ms_x").alias("part"))
        ahead = Window.orderBy("pe").rowsBetween(Window.unboundedPreceding, -1)  # p rows
        fold = F.sum if how in ("sum", "count") else agg
        carry = parts.select("pe", fold("part").over(ahead).alias("_ms_ahead"))
        local = agg("_ms_x").over(self._local().rowsBetween(Window.unboundedPreceding, 0))
        out = self._carry(rows.withColumn("_ms_l", local), carry)
        both = {"sum": F.coalesce(F.col("_ms_ahead") + F.col("_ms_l"), "_ms_l", "_ms_ahead"), "count": F.coalesce("_ms_ahead", F.lit(0)) + F.col("_ms_l"),
                "min": F.least("_ms_ahead", "_ms_l"), "max": F.greatest("_ms_ahead", "_ms_l")}[how]
        return out.withColumn(name, both).drop("_ms_x", "_ms_l", "_ms_ahead")

    def _halo(self, before: int, after: int) -> DataFrame:
        """Rows of each PE with the ``before`` rows ahead of it and the ``after`` rows behind it (``_ms_own`` marks its own)."""
        rows = self.with_rank("_ms_r")
        need = self.offsets.select(F.col("pe").alias("to"), (F.col("offset") - before).alias("lo"), F.col("offset").alias("a"), (F.col("offset") + F.col("cnt")).alias("b"),
                                 (F.col("offset") + F.col("cnt") + after).alias("hi"))
        edges = F.array_agg(F.struct("to", "lo", "a", "b", "hi"))
        table = need.agg(edges.alias("_ms_need"))
        goes = F.filter("_ms_need", lambda x: (F.col("_ms_r") >= x["lo"]) & (F.col("_ms_r") < x["hi"]) & ((F.col("_ms_r") < x["a"]) | (F.col("_ms_r") >= x["b"])))
        edge_rows = self._carry(rows, self.offsets.select("pe", F.col("offset").alias("_ms_a"), (F.col("offset") + F.col("cnt")).alias("_ms_b")))
        outside = edge_rows.where((F.col("_ms_r") < F.col("_ms_a") + after) | (F.col("_ms_r") >= F.col("_ms_b") - before)).drop("_ms_a", "_ms_b")
        copies = outside.crossJoin(F.broadcast(table)).withColumn("_ms_to", F.explode(goes)).withColumn("_ms_pe", F.col("_ms_to.to")).drop("_ms_to", "_ms_need")  # one row of p entries
        return rows.withColumn("_ms_own", F.lit(True)).unionByName(copies.withColumn("_ms_own", F.lit(False)))

    def frame(self, columns: dict[str, Column], before: int, after: int) -> DataFrame:
        """Rows with window expressions over the whole order; frames reach ``before`` rows back and ``after`` rows ahead.

        Only that many rows are copied over each border. Expressions take
        their window from ``SortedLayout.window``.
        """
        return self._halo(before, after).withColumns(columns).where("_ms_own").drop("_ms_own", "_ms_r")

    @staticmethod
    def window():
        return Window.partitionBy("_ms_pe").orderBy("_ms_r")

    def lag_lead(self, column: str, distance: int = 1) -> DataFrame:
        w = self.window()
        return self.frame({"lag": F.lag(column, distance).over(w), "lead": F.lead(column, distance).over(w)}, distance, distance)

    # ---- selection

    def range_scan(self, low=None, high=None) -> DataFrame:
        """Rows whose first key column lies in [low, high].

        PEs whose range doesn't overlap are filtered out by number, so a layout
        that was read from sorted files skips their files; one in memory is
        filtered row by row.
        """
        c = self.key.cols[0]
        inside = F.lit(True)
        first, last = (F.col("first_key.k0"), F.col("last_key.k0")) if not self.key.asc or self.key.asc[0] else (F.col("last_key.k0"), F.col("first_key.k0"))
        hit = F.lit(True)
        if low is not None:
            inside, hit = inside & (F.col(c) >= low), hit & (last >= low)
        if high is not None:
            inside, hit = inside & (F.col(c) <= high), hit & (first <= high)
        pes = [r.pe for r in self.stats.where(hit).select("pe").collect()]  # p numbers
        rows = self._plain()
        return rows.where(F.col("_ms_pe").isin(pes)).where(inside).drop("_ms_pe") if pes else rows.limit(0).drop("_ms_pe")

    def slice(self, start: int, count: int) -> DataFrame:
        """Rows at positions [start, start + count) with ``rank``; other PEs are not read on."""
        hit = [r.pe for r in self.offsets.where((F.col("offset") < start + count) & (F.col("offset") + F.col("cnt") > start)).select("pe").collect()]  # p numbers
        if not hit:
            return self.with_rank().limit(0).drop("_ms_pe")
        part = SortedLayout(self.df.where(F.col("_ms_pe").isin(hit)), self.key, self.p)
        part.offsets = self.offsets
        return part.with_rank().where(F.col("rank").between(start, start + count - 1)).drop("_ms_pe")

    def kth(self, k: int) -> DataFrame:
        return self.slice(k, 1)

    def top_k(self, k: int) -> DataFrame:
        return self.slice(0, k)

    # ---- joins and sets

    def fences(self) -> DataFrame:
        """One row for each PE that has rows: its last key; with it other tables are dealt like this one."""
        return self.stats.select("pe", "first_key", "last_key")

    def _reach(self, other: DataFrame, low: Column, high: Column) -> tuple[DataFrame, list[int]]:
        """``other`` with ``_ms_a`` and ``_ms_b``: places, among the PEs that have rows (second result), of those whose range of the first key column overlaps [low, high].

        The p first and last keys are on the driver; each row finds its places
        by binary search.
        """
        c, asc = self.key.cols[0], self.key._all[0][1]
        kind = self.df.schema[c].dataType
        one = KeySpec((c,), (asc,), (self.key._all[0][2],))

        fence = self.stats.select("pe", F.col("first_key.k0").alias("_f"), F.col("last_key.k0").alias("_l")).orderBy("pe")
        found = []
        for x in ("_f", "_l"):
            mine = fence.select("pe", F.col(x).alias(c))
            codes = Codes(mine, one)
            got = mine.orderBy("pe").select("pe", *codes.named()).toArrow()  # p rows
            found.append(codes.read([got.column(i) for i in range(1, got.num_columns)]))
        pes = got.column(0).to_pylist()
        held = other.withColumns({"_ms_lo": low.cast(kind), "_ms_hi": high.cast(kind)})
        begin, end = ("_ms_lo", "_ms_hi") if asc else ("_ms_hi", "_ms_lo")
        ends = [Codes(held, KeySpec((n,), one.asc, one.nulls_first)).columns() for n in (begin, end)]
        spot = reached(codes, *found, *ends)
        return held.withColumn("_ms_s", spot).withColumns({"_ms_a": F.col("_ms_s.a"), "_ms_b": F.col("_ms_s.b")}).drop("_ms_s"), pes

    def _dealt(self, other: DataFrame, on: str, low: Column, high: Column) -> DataFrame:
        """``other`` with the PEs (``_ms_hit``) whose range of the first key column overlaps [low, high]; none for nulls."""
        held, pes = self._reach(other, low, high)
        known = F.array(*[F.lit(x) for x in pes]) if pes else F.array().cast("array<int>")
        some = F.when(F.col("_ms_lo").isNotNull() & F.col("_ms_hi").isNotNull() & (F.col("_ms_a") <= F.col("_ms_b")),
                      F.sequence("_ms_a", "_ms_b") if pes == list(range(len(pes))) else F.transform(F.sequence("_ms_a", "_ms_b"), lambda i: F.element_at(known, i + 1)))
        return held.withColumn("_ms_hit", F.coalesce(some, F.array().cast("array<int>"))).drop("_ms_lo", "_ms_hi", "_ms_a", "_ms_b")

    def _home(self, other: DataFrame, on: Column) -> DataFrame:
        """``other`` with the PE (``_ms_pe``) where a row of key ``on`` would stand."""
        held, pes = self._reach(other, on, on)
        spot = F.least(F.col("_ms_a"), F.lit(max(0, len(pes) - 1)))
        known = F.array(*[F.lit(x) for x in pes]) if pes else F.array(F.lit(0))
        return held.withColumn("_ms_pe", spot if pes == list(range(len(pes))) else F.element_at(known, spot + 1)).drop("_ms_lo", "_ms_hi", "_ms_a", "_ms_b")

    def join(self, other: DataFrame, on: str, how: str = "inner") -> DataFrame:
        """Equi-join with ``other`` on its column ``on`` against this layout's first key column.

        ``other`` is dealt by the fences; a key that spans several PEs finds
        its partners copied to each, so this side stays balanced whatever its
        skew. Left side: this layout. ``how``: inner, left, semi, anti, right,
        full.
        """
        c = self.key.cols[0]
        dealt = self._dealt(other, on, F.col(on), F.col(on))
        copies = dealt.withColumn("_ms_to", F.explode("_ms_hit")).drop("_ms_hit").repartitionById(self.p, F.col("_ms_to"))
        here = self._plain()
        cond = (F.col("_ms_pe") == F.col("_ms_to")) & (here[c] == copies[on])
        kind = {"inner": "inner", "left": "left", "semi": "left_semi", "anti": "left_anti", "right": "inner", "full": "left"}[how]
        out = here.join(copies, cond, kind).drop("_ms_pe", "_ms_to")
        if how in ("right", "full"):  # rows of the other side without a partner: found PE by PE, as a key may be on several
            own = here.select("_ms_pe", F.col(c).alias("_ms_c")).distinct()  # a key once on each PE that has it
            met = dealt.withColumn("_ms_to", F.explode("_ms_hit")).select(F.col(on).alias("_ms_k"), "_ms_to").distinct()
            keys = met.join(own, (F.col("_ms_to") == F.col("_ms_pe")) & (F.col("_ms_k") == F.col("_ms_c")), "left_semi").select("_ms_k").distinct()
            lone = other.join(keys, F.col(on) == F.col("_ms_k"), "left_anti")
            out = out.unionByName(lone, allowMissingColumns=True)
        return out

    def band_join(self, other: DataFrame, on: str, delta) -> DataFrame:
        """Pairs whose first key column and ``on`` differ by ``delta`` at most; rows near borders are copied to each PE they reach.

        Inside of a PE rows of numbers meet in cells of twice ``delta``, of which the other side reaches three at most.
        """
        c = self.key.cols[0]
        dealt = self._dealt(other, on, F.col(on) - delta, F.col(on) + delta)
        copies = dealt.withColumn("_ms_to", F.explode("_ms_hit")).drop("_ms_hit")
        near = (F.col(c) >= F.col(on) - delta) & (F.col(c) <= F.col(on) + delta)
        here, same = self._plain(), F.col("_ms_pe") == F.col("_ms_to")
        if all(isinstance(df.schema[x].dataType, NumericType) for df, x in ((here, c), (other, on))) and isinstance(delta, int | float) and delta > 0:
            # rounding keeps the order, so a value between two others has a cell between theirs
            cell = lambda x: F.floor(x.cast("double") / (2.0 * delta))
            here = here.withColumn("_ms_cell", cell(F.col(c)))
            copies = copies.withColumn("_ms_at", F.explode(F.sequence(cell(F.col(on) - delta), cell(F.col(on) + delta))))
            same = same & (F.col("_ms_cell") == F.col("_ms_at"))
        return here.join(copies, same & near).drop("_ms_pe", "_ms_to", "_ms_cell", "_ms_at")

    def band_count(self, other: DataFrame, low: Column, high: Column, name: str = "n") -> DataFrame:
        """``other`` with the number of this layout's rows whose first key column lies in [low, high]; no pair is made.

        Each different band asks the PE of its begin for the rows before it and
        the PE of its end for the rows up to it; a PE answers by one running
        count over its different values and what it is asked.
        """
        c, (_, asc, nulls_first) = self.key.cols[0], self.key._all[0]
        if isinstance(self.df.schema[c].dataType, IntegralType):  # bounds between two integers
            low, high = F.ceil(low), F.floor(high)
        held, pes = self._reach(other, low, high)
        held = held.drop("_ms_a", "_ms_b")
        if not pes:
            return held.withColumn(name, F.lit(0).cast("long")).drop("_ms_lo", "_ms_hi")
        bands, _ = self._reach(held.select("_ms_lo", "_ms_hi").where("_ms_lo <= _ms_hi").distinct().toDF("_ms_u", "_ms_v"), F.col("_ms_u"), F.col("_ms_v"))
        known = F.array(*[F.lit(x) for x in pes])
        at = lambda x: F.element_at(known, F.greatest(F.lit(0), F.least(F.col(x), F.lit(len(pes) - 1))).cast("int") + 1)
        begin, end = ("_ms_lo", "_ms_hi") if asc else ("_ms_hi", "_ms_lo")
        ask = F.array(F.struct(at("_ms_a").alias("pe"), F.col(begin).alias("x"), F.lit(0).alias("side"), F.lit(-1).alias("sign")),
                      F.struct(at("_ms_b").alias("pe"), F.col(end).alias("x"), F.lit(2).alias("side"), F.lit(1).alias("sign")))
        asked = bands.select("_ms_lo", "_ms_hi", F.explode(ask).alias("q")).select("_ms_lo", "_ms_hi", "q.*", F.lit(0).cast("long").alias("w"))
        mine = self._plain().groupBy(F.col("_ms_pe").alias("pe"), F.col(c).alias("x")).agg(F.count("*").alias("w"), F.lit(1).alias("side"))
        order = {(True, True): F.asc_nulls_first, (True, False): F.asc_nulls_last, (False, True): F.desc_nulls_first, (False, False): F.desc_nulls_last}[asc, nulls_first]("x")
        run = Window.partitionBy("pe").orderBy(order, "side").rowsBetween(Window.unboundedPreceding, 0)
        both = mine.unionByName(asked, allowMissingColumns=True).withColumn("upto", F.sum("w").over(run))
        told = both.where("side <> 1").join(F.broadcast(self.offsets.select("pe", "offset")), "pe")  # p rows
        told = told.groupBy("_ms_lo", "_ms_hi").agg(F.sum((F.col("offset") + F.col("upto")) * F.col("sign")).alias("_ms_n")).toDF("_ms_u", "_ms_v", "_ms_n")
        out = held.join(told, (F.col("_ms_lo") == F.col("_ms_u")) & (F.col("_ms_hi") == F.col("_ms_v")), "left")
        return out.withColumn(name, F.coalesce("_ms_n", F.lit(0)).cast("long")).drop("_ms_lo", "_ms_hi", "_ms_u", "_ms_v", "_ms_n")

    def asof(self, other: DataFrame, on: str, by: list[str], value: str) -> DataFrame:
        """Rows with ``value`` of the last row of ``other`` (by column ``on``) at or before this row's first key column, for equal ``by``.

        Both are merged PE by PE; a PE's last values for each ``by`` are
        carried to the next PEs as small rows.
        """
        c = self.key.cols[0]
        theirs = self._home(other, F.col(on)).select("_ms_pe", *by, F.col(on).alias("_ms_t"), F.col(value).alias("_ms_v"), F.lit(0).alias("_ms_side"))
        mine = self._plain().withColumns({"_ms_t": F.col(c), "_ms_side": F.lit(1)})
        both = mine.unionByName(theirs.withColumn("_ms_hit", F.struct("_ms_t", "_ms_v")).drop("_ms_v"), allowMissingColumns=True)
        w = Window.partitionBy("_ms_pe", *by).orderBy("_ms_t", "_ms_side").rowsBetween(Window.unboundedPreceding, 0)
        local = both.withColumn("_ms_local", F.last("_ms_hit", True).over(w))
        ends = theirs.groupBy("_ms_pe", *by).agg(F.max(F.struct("_ms_t", "_ms_v")).alias("end"))
        keys = mine.select("_ms_pe", *by).distinct()
        carry = keys.withColumn("end", F.lit(None).cast(ends.schema["end"].dataType)).unionByName(ends).groupBy("_ms_pe", *by).agg(F.max("end").alias("end"))
        carry = carry.withColumn("_ms_prev", F.max("end").over(Window.partitionBy(*by).orderBy("_ms_pe").rowsBetween(Window.unboundedPreceding, -1))).drop("end")
        out = local.where("_ms_side = 1").join(carry, ["_ms_pe", *by], "left")
        hit = F.coalesce("_ms_local", "_ms_prev")
        return out.withColumns({f"asof_{on}": hit["_ms_t"], f"asof_{value}": hit["_ms_v"]}).select(*self.columns, f"asof_{on}", f"asof_{value}")

    def dedupe(self, keep: str = "first", of: KeySpec | None = None) -> DataFrame:
        """The first (or last) row of each run of equal keys (without ties)."""
        by = of or self.key.without_ties()
        rows = self.df.withColumn("_ms_v", F.struct(*by.names))
        out = SortedLayout(rows, self.key, self.p)
        out.offsets = self.offsets
        w = self.window()
        other = F.lag("_ms_v").over(w) if keep == "first" else F.lead("_ms_v").over(w)
        flagged = out.frame({"_ms_dup": other.isNotNull() & other.eqNullSafe(F.col("_ms_v"))}, 1, 1)
        return flagged.where("not _ms_dup").drop("_ms_dup", "_ms_v", "_ms_pe")

    def group_agg(self, by: list[str], partial: dict[str, Column], final: dict[str, Column]) -> DataFrame:
        """Groups of equal keys aggregated inside their PE; only keys on borders have more than one partial row."""
        local = self.df.groupBy("_ms_pe", *by).agg(*[v.alias(k) for k, v in partial.items()])
        return local.groupBy(*by).agg(*[v.alias(k) for k, v in final.items()])

    def rebalance(self, p: int) -> SortedLayout:
        """The same order on ``p`` PEs of equal load; every row moves at most once."""
        rows = self.with_rank("_ms_r").crossJoin(F.broadcast(self.offsets.agg(F.sum("cnt").alias("_ms_total"))))  # one row
        pe = F.expr(f"((_ms_r + 1) * {p} - 1) div _ms_total").cast("int")
        moved = rows.withColumn("_ms_pe", pe).drop("_ms_r", "_ms_total").repartitionById(p, F.col("_ms_pe"))
        n = sum(self.loads) if self.loads is not None else None
        loads = None if n is None else [n * (x + 1) // p - n * x // p for x in range(p)]
        return SortedLayout(moved.sortWithinPartitions("_ms_pe", *self.key.order()), self.key, p, loads=loads)

    # ---- more layouts

    def runs(self, first: int = 0) -> DataFrame:
        """Rows as sorted runs, one for each PE, numbered from ``first`` (``_ms_pe``) with positions from 0 (``_ms_pos``)."""
        rows = self._numbered()
        return rows.withColumn("_ms_pos", F.col("_ms_n") - 1).withColumn("_ms_pe", F.col("_ms_pe") + F.lit(first)).drop("_ms_n")

    def append(self, rows: DataFrame, p: int | None = None) -> SortedLayout:
        """This layout and new rows, sorted by themselves and then merged in."""
        from tiersort.operators.sort import merge_sort

        return merge_layouts([self, merge_sort(rows.select(*self.columns), self.key, self.p, 1)], p or self.p)

    def set_op(self, other: DataFrame, op: str, every: bool = True) -> DataFrame:
        """intersect, except or union of the key columns with those of ``other`` (same names), as multisets unless ``every`` is false.

        ``other`` is dealt by the fences and both sides are counted inside the
        PEs; only a key that spans PEs is put together from several rows.
        """
        names = [*self.key.cols]
        theirs = self._home(other, F.col(names[0])).select("_ms_pe", *names, F.lit(0).alias("_ms_l"), F.lit(1).alias("_ms_r"))
        both = self._plain().select("_ms_pe", *names, F.lit(1).alias("_ms_l"), F.lit(0).alias("_ms_r")).unionByName(theirs)
        local = both.groupBy("_ms_pe", *names).agg(F.sum("_ms_l").alias("l"), F.sum("_ms_r").alias("r"))
        return _repeated(local.groupBy(*names).agg(F.sum("l").alias("l"), F.sum("r").alias("r")), names, op, every)

    def views(self, spark=None) -> list[str]:
        """Makes temporary views of the sort's report (``ms_report``) and of the loads (``ms_loads``)."""
        spark = spark or self.df.sparkSession
        self.offsets.createOrReplaceTempView("ms_loads")
        made = ["ms_loads"]
        if self.report is not None:
            self.report.table(spark).createOrReplaceTempView("ms_report")
            made.append("ms_report")
        return made

    def explain_plan(self) -> str:
        """The physical plan of the layout's rows, as text."""
        mode = self.df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted")
        return self.df._jdf.queryExecution().explainString(mode)

    def release(self) -> None:
        """Gives cached levels back."""
        if self.report is not None:
            self.report.release()


def set_op(left: DataFrame, right: DataFrame, columns: list[str], op: str, every: bool = True) -> DataFrame:
    """intersect or except of two tables as multisets, by counting each key on either side in one exchange."""
    both = left.select(*columns, F.lit(1).alias("_ms_l"), F.lit(0).alias("_ms_r")).unionByName(right.select(*columns, F.lit(0).alias("_ms_l"), F.lit(1).alias("_ms_r")))
    counts = both.groupBy(*columns).agg(F.sum("_ms_l").alias("l"), F.sum("_ms_r").alias("r"))
    return _repeated(counts, columns, op, every)


def _repeated(counts: DataFrame, columns: list[str], op: str, every: bool, portion: int = 10_000) -> DataFrame:
    """Keys with counts (l, r) as often as the operation has them; a very frequent key is written out in portions, dealt anew."""
    n = {"intersect": F.least("l", "r"), "except": F.greatest(F.col("l") - F.col("r"), F.lit(0)), "union": F.col("l") + F.col("r")}[op]
    if not every:
        n = F.when({"intersect": (F.col("l") > 0) & (F.col("r") > 0), "except": (F.col("l") > 0) & (F.col("r") == 0), "union": F.lit(True)}[op], 1).otherwise(0).cast("long")
    some = counts.withColumn("n", n).where("n > 0").select(*columns, "n", F.explode(F.expr(f"sequence(0L, (n - 1) div {portion})")).alias("_ms_p"))
    left = F.least(F.lit(portion).cast("long"), F.col("n") - F.col("_ms_p") * portion)
    few, many = some.where(f"n <= {portion}"), some.where(f"n > {portion}").repartition(F.xxhash64(*columns, "_ms_p"))
    return few.unionByName(many).select(*columns, F.explode(F.sequence(F.lit(1).cast("long"), left)).alias("_ms_i")).select(*columns)


def merge_layouts(layouts: list[SortedLayout], p: int | None = None) -> SortedLayout:
    """Several layouts of one key as one: their PEs are runs, cut exactly and merged after one exchange."""
    from tiersort.operators.sort import Report, merge_levels
    from tiersort.sources.sinks import staged

    key, p = layouts[0].key, p or max(x.p for x in layouts)
    first, rows, report = 0, None, Report()
    for x in layouts:
        mine = x.runs(first)
        rows = mine if rows is None else rows.unionByName(mine)
        first += x.p
    rows = staged(rows, "layouts")
    report.kept.append(rows)
    return merge_levels(rows, key, p, [p], report=report)


def equi_width(df: DataFrame, column: str, low: float, high: float, m: int) -> DataFrame:
    """Rows (bucket, n): counts of m equally wide ranges of [low, high), numbered from 1; 0 is below, m + 1 above."""
    return df.groupBy(F.width_bucket(F.col(column), F.lit(low), F.lit(high), F.lit(m)).alias("bucket")).agg(F.count("*").alias("n"))


def interval_join(left: DataFrame, right: DataFrame, start: str, stop: str, other_start: str, other_stop: str, width: int) -> DataFrame:
    """Pairs of half-open integer intervals that overlap; each is copied to the cells of ``width`` it meets, and a pair is kept in the cell where it begins."""
    cell = lambda a, b: F.sequence(F.expr(f"{a} div {width}"), F.expr(f"({b} - 1) div {width}"))
    x = left.where(F.col(stop) > F.col(start)).withColumn("_ms_cell", F.explode(cell(start, stop)))
    y = right.where(F.col(other_stop) > F.col(other_start)).withColumn("_ms_cell", F.explode(cell(other_start, other_stop)))
    met = (F.col(start) < F.col(other_stop)) & (F.col(other_start) < F.col(stop))
    return x.join(y, "_ms_cell").where(met & (F.expr(f"greatest({start}, {other_start}) div {width}") == F.col("_ms_cell"))).drop("_ms_cell")
