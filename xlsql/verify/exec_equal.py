"""Execution equality of two queries: plans first, then order-free digests or sorted groups, then the rows themselves."""

from __future__ import annotations

import contextlib
import threading
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.errors import PySparkException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from xlsql.session import materialize

DIGITS = 6
#: Places that one task of the search for the group of a place covers.
SPAN = 1 << 16
#: Results of at most so many tie groups are compared from the groups' digests here; larger ones, and cuts between ties, in the cluster.
FEW = 10_000


@dataclass(frozen=True)
class EqResult:
    """``verdict``: equal, different or undecidable; ``rung``: plan, digest, ordered, exact or error; ``ambiguous_limit``: a cut between ties."""

    verdict: str
    rung: str
    ambiguous_limit: bool = False
    error: str | None = None

    @property
    def equal(self) -> bool:
        return self.verdict == "equal"


def _plain(number: Column) -> Column:
    """Decimal text without the zeros that end a fraction."""
    return F.regexp_replace(number.cast("string"), r"\.?0+$|(\.\d*?)0+$", "$1")


def _number(c: Column, kind: T.DataType, digits: int) -> Column:
    if isinstance(kind, T.DecimalType):
        return F.when(F.instr(F.round(c, digits).cast("string"), ".") > 0, _plain(F.round(c, digits))).otherwise(c.cast("string"))
    if not isinstance(kind, (T.FloatType, T.DoubleType)):
        return c.cast("string")
    d = c.cast("double")
    size = F.abs(d)
    small = F.round(d, digits).cast("decimal(38,6)")
    text = F.when(size < 1e15, _plain(F.when(size < 1e15, small))).when(size < 9.2e18, F.when(size < 9.2e18, d).cast("bigint").cast("string"))
    return F.when(F.isnan(d), "nan").otherwise(text.when(size < 1e31, _plain(F.when(size < 1e31, d).cast("decimal(38,6)"))).otherwise(d.cast("string")))


def canonical_cell(c: Column, kind: T.DataType, digits: int = DIGITS) -> Column:
    """Text of a cell by which results compare; "" is null, anything else begins with "=".

    Numbers of any type are alike: doubles are rounded to ``digits`` places, whole ones are exact up to 9.2e18; NaN equals itself and
    0 equals -0. A date equals midnight of it. Arrays, structs (by position) and maps (in any order) follow the same rules inside.
    """
    if isinstance(kind, T.NumericType):
        text = _number(c, kind, digits)
    elif isinstance(kind, T.DateType):
        text = F.concat(c.cast("string"), F.lit(" 00:00:00"))
    elif isinstance(kind, T.BinaryType):
        text = F.hex(c)
    elif isinstance(kind, T.ArrayType):
        text = F.to_json(F.transform(c, lambda x: canonical_cell(x, kind.elementType, digits)))
    elif isinstance(kind, T.StructType):
        text = F.to_json(F.array(*[canonical_cell(c[f.name], f.dataType, digits) for f in kind.fields])) if kind.fields else F.lit("[]")
        text = F.when(c.isNotNull(), text)
    elif isinstance(kind, T.MapType):
        pair = lambda e: F.array(canonical_cell(e["key"], kind.keyType, digits), canonical_cell(e["value"], kind.valueType, digits))
        text = F.to_json(F.array_sort(F.transform(F.map_entries(c), pair)))
    else:
        text = c.cast("string")
    return F.when(c.isNull(), F.lit("")).otherwise(F.concat(F.lit("="), text))


def canonical_row(df: DataFrame, digits: int = DIGITS) -> DataFrame:
    """One array column ``row``: cells by position, so that names do not matter."""
    named = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    return named.select(F.array(*[canonical_cell(F.col(f.name), f.dataType, digits) for f in named.schema.fields]).alias("row"))


def _hashes() -> tuple[Column, Column]:
    return F.xxhash64("row"), F.xxhash64(F.lit(7), F.col("row"))


def digest(df: DataFrame) -> DataFrame:
    """One row: n, two sums of differently seeded hashes, xor. One pass, nothing is shuffled but one partial row for each task."""
    a, b = _hashes()
    return canonical_row(df).agg(F.count("*").alias("n"), F.sum(a.cast("decimal(38,0)")).alias("sum_a"), F.sum(b.cast("decimal(38,0)")).alias("sum_b"), F.bit_xor(a).alias("xor_a"))


def exact_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows whose multiplicities differ (row, surplus): one union, one aggregation."""
    both = canonical_row(a).withColumn("side", F.lit(1)).unionByName(canonical_row(b).withColumn("side", F.lit(-1)))
    return both.groupBy("row").agg(F.sum("side").alias("surplus")).where("surplus <> 0")


# ------------------------------------------------------------------------------------------------------------------- order


@dataclass(frozen=True)
class Arranged:
    """A result with its order: the rows that it chooses from (sort keys k0, k1 and so on, ``row``), how the keys sort, and what OFFSET and LIMIT leave."""

    rows: DataFrame
    sorts: tuple[Column, ...]
    skip: int
    take: int | None

    @property
    def keys(self) -> list[str]:
        return [f"k{i}" for i in range(len(self.sorts))]

    @property
    def limited(self) -> bool:
        return self.skip > 0 or self.take is not None


def arranged(df: DataFrame, digits: int = DIGITS) -> Arranged:
    """Take a query's top-level ORDER BY, OFFSET and LIMIT from its analysed plan.

    The plan knows sort keys that the result does not show, expressions, aliases, ordinals, and where nulls go. Doubles among the keys are
    rounded like cells, so that sums in another order tie alike. A result without ORDER BY has no keys.
    """
    from pyspark.sql.classic.column import Column as ClassicColumn

    spark = df.sparkSession
    jvm, root = spark._jvm, df._jdf.queryExecution().analyzed()
    node, skip, take = root.plan() if root.nodeName() == "WithCTE" else root, 0, None
    while node.nodeName() in ("GlobalLimit", "LocalLimit", "Offset"):
        if node.nodeName() == "GlobalLimit":
            take = node.limitExpr().eval(None)
        elif node.nodeName() == "Offset":
            skip = node.offsetExpr().eval(None)
        node = node.child()
    shown, orders = node.output(), []
    below = node
    if node.nodeName() == "Project" and node.child().nodeName() == "Sort":
        plain = [node.projectList().apply(i).getClass().getSimpleName() == "AttributeReference" for i in range(node.projectList().size())]
        below = node.child() if all(plain) else node
    if below.nodeName() == "Sort":
        orders, node = [below.order().apply(i) for i in range(below.order().size())], below.child()
    if root.nodeName() == "WithCTE":
        node = root.copy(node, root.cteDefs())
    base = DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, node), spark)
    column = lambda e: ClassicColumn(jvm.org.apache.spark.sql.classic.ExpressionUtils.column(e))
    keys, sorts = [], []
    for i, o in enumerate(orders):
        key = column(o.child())
        keys.append((F.round(key, digits) if o.child().dataType().typeName() in ("double", "float") else key).alias(f"k{i}"))
        down, last = o.direction().sql() == "DESC", o.nullOrdering().sql() == "NULLS LAST"
        k = F.col(f"k{i}")
        sorts.append((k.desc_nulls_last() if last else k.desc_nulls_first()) if down else (k.asc_nulls_last() if last else k.asc_nulls_first()))
    cells = [canonical_cell(column(shown.apply(i)), f.dataType, digits) for i, f in enumerate(df.schema.fields)]
    return Arranged(base.select(*keys, F.array(*cells).alias("row")), tuple(sorts), skip, take)


def _groups(x: Arranged, size: int, table: DataFrame) -> DataFrame:
    """keys, begin, end, cut, uniform, n, sum_a, sum_b of the tie groups within the window: places from 0 on, whole groups' digests.

    Groups are sorted after they are counted, so a key that many rows share is one row here; each task adds up its own groups, and
    the offset of the tasks is a table of one row for each task.
    """
    whole = Window.partitionBy("part").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
    # one row for each task
    tasks = table.groupBy("part").agg(F.sum("n").alias("rows")).withColumn("ahead", F.coalesce(F.sum("rows").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    start = F.col("ahead") + F.coalesce(F.sum("n").over(whole), F.lit(0)) - x.skip
    placed = table.join(F.broadcast(tasks.drop("rows")), "part").withColumn("start", start)
    ends = F.col("start") + F.col("n")
    placed = placed.withColumn("begin", F.greatest("start", F.lit(0))).withColumn("end", F.least(ends, F.lit(size))).withColumn("cut", (F.col("start") < 0) | (ends > size))
    return placed.where("begin < end").select(*x.keys, "begin", "end", "cut", "uniform", "n", "sum_a", "sum_b", "hash_a", "hash_b")


def _tie_groups(x: Arranged) -> DataFrame:
    """keys, n, uniform, sums and least values of two hashes of each tie group; partial sums meet, so a key that many rows share is no hot spot."""
    a, b = _hashes()
    sums = [F.sum(h.cast("decimal(38,0)")).alias(f"sum_{s}") for h, s in ((a, "a"), (b, "b"))] + [F.min(a).alias("hash_a"), F.min(b).alias("hash_b"), (F.min(a) == F.max(a)).alias("uniform")]
    return x.rows.groupBy(*x.keys).agg(F.count("*").alias("n"), *sums).where("n > 0")


def _table(x: Arranged) -> tuple[Arranged, DataFrame, int]:
    """The rows written once, the sorted table of their tie groups, and the number of rows."""
    held = Arranged(materialize(x.rows, "arranged"), x.sorts, x.skip, x.take)
    groups = _tie_groups(held)
    groups = (groups.orderBy(*x.sorts) if x.sorts else groups).withColumn("id", F.monotonically_increasing_id())
    table = materialize(groups.withColumn("part", F.shiftright("id", 33)), "groups")
    return held, table, table.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def _window(x: Arranged, n: int) -> int:
    """Rows that OFFSET and LIMIT leave of ``n``."""
    return min(max(0, n - x.skip), n if x.take is None else x.take)


def _small_equal(a: Arranged, b: Arranged) -> EqResult | None:
    """``ordered_equal`` from at most ``FEW`` digests of tie groups on each side; None if there are more, or a cut between ties of ``a``."""
    sides = []
    for x in (a, b):
        table = _tie_groups(x)
        rows = (table.orderBy(*x.sorts) if x.sorts else table).limit(FEW + 1).collect()
        if len(rows) > FEW:
            return None
        sides.append(rows)
    size = _window(a, sum(r["n"] for r in sides[0]))
    if size != _window(b, sum(r["n"] for r in sides[1])):
        return EqResult("different", "ordered")
    placed = []
    for x, rows in zip((a, b), sides):
        at, held = -x.skip, []
        for r in rows:
            begin, end = max(at, 0), min(at + r["n"], size)
            if begin < end:
                held.append((begin, end, begin != at or end != at + r["n"], r))
            at += r["n"]
        placed.append(held)
    if any(cut for _, _, cut, _ in placed[0]):
        return None
    theirs, unsure = {p[0]: p for p in placed[1]}, False
    if not {p[0] for p in placed[0]} <= set(theirs):
        return EqResult("different", "ordered")
    order, i = sorted(theirs), 0
    for _, end, _, r in placed[0]:
        sums = [0, 0]
        while i < len(order) and order[i] < end:
            begin, stop, cut, q = theirs[order[i]]
            unsure |= cut
            if cut and not q["uniform"]:
                return EqResult("different", "ordered")
            for k, s in enumerate("ab"):
                sums[k] += q[f"hash_{s}"] * (stop - begin) if cut else int(q[f"sum_{s}"])
            i += 1
        if sums != [int(r["sum_a"]), int(r["sum_b"])]:
            return EqResult("different", "ordered")
    return EqResult("equal", "ordered", unsure)


def _owners(mine: DataFrame, theirs: DataFrame) -> DataFrame:
    """Add ``owner`` to ``theirs``: the begin of the group of ``mine`` in which each begins. Both cover the same places; work is cut into spans of ``SPAN`` places."""
    spans = F.sequence((F.col("begin") / SPAN).cast("long"), ((F.col("end") - 1) / SPAN).cast("long"))
    marks = mine.select("begin", "end", F.explode(spans).alias("span")).select("span", F.greatest("begin", F.col("span") * SPAN).alias("at"), F.col("begin").alias("owner"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("begin"))
    asks = theirs.select((F.col("begin") / SPAN).cast("long").alias("span"), F.col("begin").alias("at"), F.lit(None).cast("long").alias("owner"), F.lit(1).alias("side"), "begin")
    w = Window.partitionBy("span").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, 0)
    found = marks.unionByName(asks).withColumn("owner", F.last("owner", True).over(w)).where("side = 1").select("begin", "owner")
    return theirs.join(found, "begin")


def ordered_equal(a: Arranged, b: Arranged) -> EqResult:
    """Whether every result that ``b`` may give is one that ``a`` may give.

    Rows that tie on all of ``a``'s keys may come in any order, and where a LIMIT or OFFSET cuts through such a group any of its rows may be
    chosen. So each group of ``a`` must begin where a group of ``b`` begins; a group that lies wholly in the window must equal, as a bag, what
    ``b`` has in its places; in the places of a cut group all that ``b`` may put there must be a sub-bag of the whole group.
    """
    small = _small_equal(a, b)
    if small:
        return small
    (a, groups_a, n_a), (b, groups_b, n_b) = _table(a), _table(b)
    size = _window(a, n_a)
    if size != _window(b, n_b):
        return EqResult("different", "ordered")
    if not size:
        return EqResult("equal", "ordered")
    mine, theirs = _groups(a, size, groups_a), _groups(b, size, groups_b)
    if not mine.join(theirs, "begin", "left_anti").isEmpty():
        return EqResult("different", "ordered")
    flags = mine.select("begin", F.col("cut").alias("open"))
    theirs = materialize(_owners(mine, theirs).join(flags.withColumnRenamed("begin", "owner"), "owner"), "owned")
    # of a cut group only equal rows are sure to be what fills its places
    share = lambda s: F.when(F.col("cut"), F.when(F.col("uniform"), F.col(f"hash_{s}").cast("decimal(38,0)") * (F.col("end") - F.col("begin")))).otherwise(F.col(f"sum_{s}"))
    closed = theirs.where("not open").withColumn("a", share("a")).withColumn("b", share("b"))
    sums = closed.groupBy("owner").agg(F.sum("a").alias("a"), F.sum("b").alias("b"), F.max((F.col("cut") & ~F.col("uniform")).cast("int")).alias("unsure"))
    wrong = mine.where("not cut").join(sums, F.col("begin") == F.col("owner")).where((F.col("unsure") == 1) | (F.col("a") != F.col("sum_a")) | (F.col("b") != F.col("sum_b")))
    if not wrong.isEmpty():
        return EqResult("different", "ordered")
    # at most the first and the last group are cut
    cut = mine.where("cut").select(*a.keys, F.col("begin").alias("owner"))
    if cut.isEmpty():
        return EqResult("equal", "ordered", not theirs.where("cut").isEmpty())
    same = lambda left, right, keys: [left[k].eqNullSafe(right[k]) for k in keys]
    mixed = lambda rows, groups, keys: rows.join(groups, same(rows, groups, keys)) if keys else rows.crossJoin(groups)
    whole = mixed(a.rows, F.broadcast(cut), a.keys).groupBy("owner", "row").agg(F.count("*").alias("held"))
    asked = theirs.where("open").select(*b.keys, "owner", "begin", F.when(F.col("cut"), F.col("end") - F.col("begin")).alias("places"))
    # without keys there is one group
    asked = mixed(b.rows, asked if b.keys else F.broadcast(asked), b.keys).groupBy("owner", "begin", "row").agg(F.least(F.count("*"), F.max("places")).alias("most"))
    wanted = asked.groupBy("owner", "row").agg(F.sum("most").alias("wanted"))
    over = wanted.join(whole, ["owner", "row"], "left").where(F.col("wanted") > F.coalesce("held", F.lit(0)))
    return EqResult("equal" if over.isEmpty() else "different", "ordered", True)


# ------------------------------------------------------------------------------------------------------------------- ladder


class DigestCache:
    """Digests by plan and snapshot, so that a text that methods and runs share is executed once; threads may share it."""

    def __init__(self):
        self.held: dict[tuple[str, int], tuple] = {}
        self.runs = 0
        self.lock = threading.Lock()

    def get(self, df: DataFrame, snapshot: str) -> tuple:
        key = (snapshot, df.semanticHash())
        if key not in self.held:
            found = tuple(digest(df).first())
            with self.lock:
                self.runs += 1
                self.held[key] = found
        return self.held[key]


def exec_equal(a: DataFrame, b: DataFrame, ordered: bool = False, as_set: bool = False, level: str = "auto", cache: DigestCache | None = None, snapshots: tuple[str, str] = ("a", "b")) -> EqResult:
    """Compare two results.

    ``level``: plan, digest, exact, or auto, which takes the first rung that decides. ``ordered``: the order that ``a`` asks for counts (``ordered_equal``).
    Where a LIMIT leaves the choice of rows open, any choice is right, ordered or not. A plan that is not deterministic is undecidable.
    """
    if len(a.columns) != len(b.columns):
        return EqResult("different", "plan")
    if not all(df._jdf.queryExecution().analyzed().deterministic() for df in (a, b)):
        return EqResult("undecidable", "plan")
    if level in ("auto", "plan"):
        try:
            if a.sameSemantics(b):
                return EqResult("equal", "plan")
        except PySparkException:
            pass
        if level == "plan":
            return EqResult("undecidable", "plan")
    if as_set:
        a, b = a.distinct(), b.distinct()
    x, y = arranged(a), arranged(b)
    if ordered and x.sorts:
        return ordered_equal(x, y)
    if level in ("auto", "digest"):
        found = [cache.get(df, s) if cache else tuple(digest(df).first()) for df, s in zip((a, b), snapshots)]
        result = EqResult("equal" if found[0] == found[1] else "different", "digest")
    else:
        result = EqResult("equal" if exact_difference(a, b).isEmpty() else "different", "exact")
    if not result.equal and (x.limited or y.limited):
        return ordered_equal(x, y)
    return result


@contextlib.contextmanager
def deadline(session: SparkSession, seconds: float | None):
    """Cancel what runs inside after so many seconds; the cancelled action raises."""
    if seconds is None:
        yield
        return
    context, group = session.sparkContext, f"deadline-{uuid.uuid4().hex}"
    context.setJobGroup(group, "bounded", True)
    timer = threading.Timer(seconds, context.cancelJobGroup, [group])
    timer.start()
    try:
        yield
    finally:
        timer.cancel()
        context.setLocalProperty("spark.jobGroup.id", None)


def run_pair(session_a: SparkSession, sql_a: str, session_b: SparkSession, sql_b: str, mode: str = "auto", level: str = "auto", seconds: float | None = None, cache: DigestCache | None = None, snapshots: tuple[str, str] = ("a", "b")) -> EqResult:
    """Execution equality of two texts on two databases; ``mode``: auto and ordered (the order of the first text counts if it asks for one), bag, set.

    With ``seconds`` a pair that runs longer is cancelled and counts as different, with rung error.
    """
    try:
        with deadline(session_a, seconds):
            return exec_equal(session_a.sql(sql_a), session_b.sql(sql_b), mode in ("auto", "ordered"), mode == "set", level, cache, snapshots)
    except PySparkException as e:
        return EqResult("different", "error", error=str(e).split("\n")[0][:200])
    except Exception as e:
        if seconds is None:
            raise
        return EqResult("different", "error", error=str(e).split("\n")[0][:200])


def run_pairs(pairs: list[tuple[SparkSession, str, SparkSession, str]], mode: str = "auto", seconds: float | None = None, workers: int = 8, cache: DigestCache | None = None, snapshots: tuple[str, str] = ("a", "b")) -> list[EqResult]:
    """``run_pair`` of many pairs, ``workers`` of them at a time; each distinct plan's digest is taken once."""
    cache = cache or DigestCache()
    with ThreadPoolExecutor(workers) as pool:
        return list(pool.map(lambda p: run_pair(*p, mode=mode, seconds=seconds, cache=cache, snapshots=snapshots), pairs))
