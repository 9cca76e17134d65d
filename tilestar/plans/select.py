"""Which of unlike workers gets the next message: steady-state rates, and greedy ratio selection.

A platform is one row: workers sorted by id, as an array of (worker_id, c, w, g, send, gain, square): times of a message and of a C square, updates that a message brings. Selection is sequential, so it is a fold inside the row, and platforms
run in parallel. Ratios are compared by cross-multiplication of whole numbers, ties go to the worker that comes first.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

WORKER = "array<struct<worker_id:int,c:bigint,w:bigint,g:bigint,send:bigint,gain:bigint,square:bigint>>"


def bandwidth_first(platform: DataFrame, fractional: bool = True) -> DataFrame:
    """Workers by 2c/g ascending, enrolled while the port lasts: share of a worker's full speed, and its rate.

    fractional: the first worker for whom the port does not suffice takes what is left.
    """
    load = 2.0 * F.col("c") / (F.col("g") * F.col("w"))
    order = Window.partitionBy("platform_id").orderBy(2.0 * F.col("c") / F.col("g"), "worker_id")
    rows = platform.filter("g > 0").withColumn("load", load).withColumn("upto", F.sum("load").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    rest = 1.0 - (F.col("upto") - F.col("load"))
    share = F.greatest(F.lit(0.0), F.least(F.lit(1.0), rest / F.col("load"))) if fractional else F.when(F.col("upto") <= 1.0 + 1e-12, 1.0).otherwise(0.0)
    return rows.withColumn("share", share).withColumn("rate", F.col("share") / F.col("w")).drop("upto")


def rates(platform: DataFrame) -> DataFrame:
    """(platform_id, rate, rate_whole, enrolled): the linear program's bound, and with whole workers only."""
    part = bandwidth_first(platform).groupBy("platform_id").agg(F.sum("rate").alias("rate"), F.sum(F.when(F.col("share") > 0, 1).otherwise(0)).alias("enrolled"))
    whole = bandwidth_first(platform, fractional=False).groupBy("platform_id").agg(F.sum("rate").alias("rate_whole"))
    return part.join(whole, "platform_id")


def buffer_demand(platform: DataFrame) -> DataFrame:
    """Buffers a worker needs to compute through the longest panel of any other enrolled worker, against those it has."""
    own = bandwidth_first(platform).filter("share > 0")
    every = Window.partitionBy("platform_id")
    longest = F.max(2 * F.col("c") * F.col("g")).over(every)
    rows = own.withColumn("wait", longest)
    need = 2 * F.col("g") * F.ceil(F.col("wait") / (F.col("w") * F.col("g") * F.col("g")).cast("double")) + F.col("g") * F.col("g") + 2 * F.col("g")
    return rows.select("platform_id", "worker_id", "m", "g", "wait", need.cast("bigint").alias("need"), (need <= F.col("m")).alias("fits"))


def _less(n1: Column, d1: Column, n2: Column, d2: Column) -> Column:
    wide = lambda x: x.cast("decimal(19,0)")
    return wide(n1) * wide(d2) < wide(n2) * wide(d1)


def _argmax(n: Column, ratio) -> Column:
    """First index below n of the greatest ratio(index) = (num, den)."""
    zero = F.struct(F.lit(0).alias("k"), F.lit(0).cast("bigint").alias("num"), F.lit(1).cast("bigint").alias("den"))

    def better(best: Column, k: Column) -> Column:
        num, den = ratio(k)
        return F.when((k == 0) | _less(best["num"], best["den"], num, den), F.struct(k.alias("k"), num.cast("bigint").alias("num"), den.cast("bigint").alias("den"))).otherwise(best)

    return F.aggregate(F.sequence(F.lit(0), n - 1), zero, better)["k"]


def fold(platforms: DataFrame, steps: Column | int, rule: str, lead: str = "workers", charge_c: int | None = None) -> DataFrame:
    """platforms with an array `workers`: adds picks (worker ids), ends and work after each step.

    rule: global, local; global2, local2 commit the best pair of messages; global2_receding, local2_receding commit its first.
    charge_c: inner steps of a chunk, if its C square is to be charged: the first of so many messages to a worker brings it, and takes back the one before.
    """
    local, pair, recede = rule.startswith("local"), "2" in rule, rule.endswith("receding")
    ws = F.col(lead)
    long_ = lambda x: x.cast("bigint")
    start = F.struct(
        F.lit(0).cast("bigint").alias("work"),
        F.lit(0).cast("bigint").alias("comm"),
        F.transform(ws, lambda w: F.lit(0).cast("bigint")).alias("ready"),
        F.transform(ws, lambda w: F.lit(0).cast("bigint")).alias("sent"),
        F.array().cast("array<int>").alias("picks"),
        F.array().cast("array<bigint>").alias("ends"),
        F.array().cast("array<bigint>").alias("works"),
    )

    def cost(w: Column, sent: Column) -> Column:
        if charge_c is None:
            return w["send"]
        return w["send"] + F.when(sent % charge_c == 0, F.when(sent == 0, w["square"]).otherwise(2 * w["square"])).otherwise(0)

    arrive = lambda comm, ready, w, sent: F.greatest(comm + cost(w, sent), ready)

    def send(s: Column, k: Column) -> Column:
        w = ws[k]
        end = arrive(s["comm"], s["ready"][k], w, s["sent"][k])
        work = s["work"] + w["gain"]
        return F.struct(
            long_(work).alias("work"),
            long_(end).alias("comm"),
            F.transform(s["ready"], lambda r, i: F.when(i == k, end + w["gain"] * w["w"]).otherwise(r)).alias("ready"),
            F.transform(s["sent"], lambda n, i: F.when(i == k, n + 1).otherwise(n)).alias("sent"),
            F.concat(s["picks"], F.array(w["worker_id"])).alias("picks"),
            F.concat(s["ends"], F.array(long_(end))).alias("ends"),
            F.concat(s["works"], F.array(long_(work))).alias("works"),
        )

    def one(s: Column):
        def ratio(k: Column):
            w = ws[k]
            if local:
                return w["gain"], F.greatest(cost(w, s["sent"][k]), s["ready"][k] - s["comm"])
            return s["work"] + w["gain"], arrive(s["comm"], s["ready"][k], w, s["sent"][k])

        return ratio

    def two(s: Column):
        def ratio(n: Column):
            p = F.size(ws)
            i, j = F.floor(n / p).cast("int"), (n % p).cast("int")
            a, b = ws[i], ws[j]
            first = arrive(s["comm"], s["ready"][i], a, s["sent"][i])
            ready = F.when(i == j, first + a["gain"] * a["w"]).otherwise(s["ready"][j])
            second = arrive(first, ready, b, s["sent"][j] + F.when(i == j, 1).otherwise(0))
            gain = a["gain"] + b["gain"]
            return (gain, second - s["comm"]) if local else (s["work"] + gain, second)

        return ratio

    def step(s: Column, n: Column) -> Column:
        if not pair:
            return F.transform(F.array(_argmax(F.size(ws), one(s))), lambda k: send(s, k))[0]
        p = F.size(ws)
        best = F.array(_argmax(p * p, two(s)))
        first = F.transform(best, lambda n: send(s, F.floor(n / p).cast("int")))[0]
        return first if recede else F.transform(F.array(F.struct(first.alias("s"), best[0].alias("n"))), lambda x: send(x["s"], (x["n"] % p).cast("int")))[0]

    count = F.lit(steps) if isinstance(steps, int) else steps
    rounds = F.floor((count + 1) / 2).cast("int") if pair and not recede else count.cast("int")
    done = F.aggregate(F.sequence(F.lit(1), rounds), start, step)
    return platforms.withColumn("done", done).select(*platforms.columns, "done.picks", "done.ends", "done.works")


def as_rows(platform: DataFrame) -> DataFrame:
    """(platform_id, workers): a row per platform, workers that have a side, by id. Columns send, gain and square, where there are any, replace those of the product."""
    g, c = F.col("g"), F.col("c")
    usual = {"send": 2 * g * c, "gain": g * g, "square": g * g * c}
    own = platform.filter("g > 0").withColumns({k: v for k, v in usual.items() if k not in platform.columns})
    worker = F.struct("worker_id", "c", "w", "g", "send", "gain", "square")
    return own.groupBy("platform_id").agg(F.sort_array(F.collect_list(worker)).cast(WORKER).alias("workers"))


def until_owned(r: int, t: int, s: int) -> Column:
    """Steps after which, whoever they went to, workers own s columns: no worker needs more messages a column, and each may have a block under way."""
    per = lambda w: t * F.ceil(F.lit(r) / w["g"])
    ws = F.col("workers")
    slowest = F.array_max(F.transform(ws, lambda w: F.ceil(per(w) * (s + w["g"]) / w["g"])))
    return (slowest + F.aggregate(ws, F.lit(0).cast("bigint"), lambda n, w: n + per(w))).cast("int")


def trace(folded: DataFrame) -> DataFrame:
    """(platform_id, step, worker_id, finish, work)."""
    each = F.posexplode(F.arrays_zip("picks", "ends", "works")).alias("n", "x")
    return folded.select("platform_id", each).select("platform_id", (F.col("n") + 1).alias("step"), F.col("x.picks").alias("worker_id"), F.col("x.ends").alias("finish"), F.col("x.works").alias("work"))


def asymptotic_ratio(folded: DataFrame) -> DataFrame:
    """Work per unit of communication time at the last step."""
    return folded.select("platform_id", (F.element_at("works", -1) / F.element_at("ends", -1).cast("double")).alias("ratio"))


def check_rate_bound(folded: DataFrame, platform: DataFrame) -> DataFrame:
    """Steps at which the work that has been computed beats the steady-state bound by more than the squares still under way: expected none."""
    slack = platform.groupBy("platform_id").agg(F.sum(F.col("g") * F.col("g")).alias("slack"))
    rows = trace(folded).join(rates(platform), "platform_id").join(slack, "platform_id")
    return rows.filter(F.col("work") > F.col("rate") * F.col("finish") + F.col("slack") + 1e-6).select("platform_id", "step")


def preallocate(picks: DataFrame, platform: DataFrame, r: int, t: int, s: int) -> DataFrame:
    """Columns that each worker owns when s columns are complete: g columns after every t * ceil(r/g) picks. (platform_id, worker_id, columns, step)."""
    steps = picks.join(platform.select("platform_id", "worker_id", "g"), ["platform_id", "worker_id"])
    own = Window.partitionBy("platform_id", "worker_id").orderBy("step")
    rows = steps.withColumn("nth", F.row_number().over(own)).withColumn("per", t * F.ceil(F.lit(r) / F.col("g")))
    rows = rows.withColumn("gain", F.when(F.col("nth") % F.col("per") == 0, F.col("g")).otherwise(0))
    upto = Window.partitionBy("platform_id").orderBy("step").rowsBetween(Window.unboundedPreceding, -1)
    used = rows.withColumn("before", F.coalesce(F.sum("gain").over(upto), F.lit(0))).filter(F.col("before") < s)
    return used.groupBy("platform_id", "worker_id").agg(F.sum("gain").cast("bigint").alias("columns"), F.count("*").alias("picks"))


def selection_sql(platform_sql: str, steps: int, local: bool = False, charge_c: int | None = None, message: tuple[str, str] = ("2 * g * c", "g * g")) -> str:
    """The greedy as a recursive query: DuckDB. message: its time and its updates, over the platform's columns."""
    cost = "num.send"
    if charge_c is not None:
        cost += f" + CASE WHEN st.sent[num.k] % {charge_c} = 0 THEN num.g * num.g * num.c * CASE WHEN st.sent[num.k] = 0 THEN 1 ELSE 2 END ELSE 0 END"
    ratio = "gain::DOUBLE / greatest(cost, rd - comm)" if local else "(work + gain)::DOUBLE / greatest(comm + cost, rd)"
    return f"""
WITH RECURSIVE pf AS ({platform_sql}),
num AS (SELECT platform_id, worker_id, c, w, g, {message[0]} AS send, {message[1]} AS gain, row_number() OVER (PARTITION BY platform_id ORDER BY worker_id) AS k FROM pf WHERE g > 0),
st AS (
  SELECT platform_id, 0 AS step, 0::BIGINT AS work, 0::BIGINT AS comm, list(0::BIGINT) AS ready, list(0::BIGINT) AS sent, 0 AS worker_id FROM num GROUP BY platform_id
  UNION ALL
  SELECT st.platform_id, st.step + 1, st.work + x.gain, x.fin, list_transform(st.ready, lambda v, i: CASE WHEN i = x.k THEN x.fin + x.gain * x.w ELSE v END),
         list_transform(st.sent, lambda v, i: CASE WHEN i = x.k THEN v + 1 ELSE v END), x.worker_id
  FROM st, LATERAL (SELECT n.*, greatest(st.comm + n.cost, st.ready[n.k]) AS fin
                    FROM (SELECT num.*, {cost} AS cost, st.ready[num.k] AS rd, st.work AS work, st.comm AS comm FROM num WHERE num.platform_id = st.platform_id) n
                    ORDER BY {ratio} DESC, n.k LIMIT 1) x
  WHERE st.step < {steps})
SELECT platform_id, step, worker_id, comm AS finish, work FROM st WHERE step > 0
"""


def pair_sql(platform_sql: str, steps: int, local: bool = False, recede: bool = False) -> str:
    """The two-step look-ahead as a recursive query: DuckDB. A row of the recursion holds one message where the first is kept, two where the pair is."""
    gain = "a.g * a.g + b.g * b.g"
    ratio = f"({gain})::DOUBLE / (f2 - comm)" if local else f"(work + {gain})::DOUBLE / f2"
    last = "f1, work + p.ga * p.ga, p.ka, p.ga, p.wa" if recede else "f2, work + p.ga * p.ga + p.gb * p.gb, p.kb, p.gb, p.wb"
    comm, work, *_ = last.split(", ")
    after = "list_transform(ready, lambda v, i: CASE WHEN i = p.ka THEN p.f1 + p.ga * p.ga * p.wa ELSE v END)"
    if not recede:
        after = f"list_transform({after}, lambda v, i: CASE WHEN i = p.kb THEN p.f2 + p.gb * p.gb * p.wb ELSE v END)"
    rounds = steps if recede else (steps + 1) // 2
    first = "SELECT platform_id, {n} AS step, wa AS worker_id, c1 AS finish, w1 AS work FROM st WHERE n > 0"
    each = first.format(n="n") if recede else first.format(n="2 * n - 1") + " UNION ALL SELECT platform_id, 2 * n, wb, comm, work FROM st WHERE n > 0"
    return f"""
WITH RECURSIVE pf AS ({platform_sql}),
num AS (SELECT platform_id, worker_id, c, w, g, row_number() OVER (PARTITION BY platform_id ORDER BY worker_id) AS k FROM pf WHERE g > 0),
st AS (
  SELECT platform_id, 0 AS n, 0::BIGINT AS work, 0::BIGINT AS comm, list(0::BIGINT) AS ready, 0 AS wa, 0 AS wb, 0::BIGINT AS c1, 0::BIGINT AS w1 FROM num GROUP BY platform_id
  UNION ALL
  SELECT st.platform_id, st.n + 1, st.{work}, p.{comm}, {after}, p.ia, p.ib, p.f1, st.work + p.ga * p.ga
  FROM st, LATERAL (
    SELECT z.* FROM (
      SELECT y.*, greatest(y.f1 + 2 * y.gb * y.cb, CASE WHEN y.ka = y.kb THEN y.f1 + y.ga * y.ga * y.wa ELSE st.ready[y.kb] END) AS f2, st.work AS work, st.comm AS comm
      FROM (SELECT a.k AS ka, a.g AS ga, a.w AS wa, a.worker_id AS ia, b.k AS kb, b.g AS gb, b.w AS wb, b.c AS cb, b.worker_id AS ib,
                   greatest(st.comm + 2 * a.g * a.c, st.ready[a.k]) AS f1
            FROM num a JOIN num b ON a.platform_id = b.platform_id WHERE a.platform_id = st.platform_id) y) z
    ORDER BY {ratio.replace("a.g", "ga").replace("b.g", "gb")} DESC, ka, kb LIMIT 1) p
  WHERE st.n < {rounds})
{each}
"""


def preallocate_sql(platform_sql: str, steps: int, r: int, t: int, s: int) -> str:
    """The columns that the global greedy's workers own, as `preallocate` gives them: DuckDB."""
    return f"""
WITH tr AS ({selection_sql(platform_sql, steps)}),
x AS (SELECT tr.platform_id, tr.worker_id, step, g, row_number() OVER (PARTITION BY tr.platform_id, tr.worker_id ORDER BY step) AS nth
      FROM tr JOIN ({platform_sql}) p ON p.platform_id = tr.platform_id AND p.worker_id = tr.worker_id),
y AS (SELECT *, CASE WHEN nth % ({t} * (({r} + g - 1) // g)) = 0 THEN g ELSE 0 END AS gain FROM x),
z AS (SELECT *, coalesce(sum(gain) OVER (PARTITION BY platform_id ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM y)
SELECT platform_id, worker_id, sum(gain)::BIGINT AS columns, count(*)::BIGINT AS picks FROM z WHERE before < {s} GROUP BY 1, 2
"""


def waits(folded: DataFrame, platform: DataFrame) -> DataFrame:
    """From a trace: each worker's longest time between the ends of two of its messages, how often it computed all it held before the next came, and the
    buffers that would have carried it through: (platform_id, worker_id, messages, longest, starved, need, fits). Fits: need within the double buffer's m."""
    own = Window.partitionBy("platform_id", "worker_id").orderBy("step")
    rows = trace(folded).withColumn("gap", F.col("finish") - F.lag("finish").over(own)).join(platform, ["platform_id", "worker_id"])
    panel = F.col("g") * F.col("g") * F.col("w")
    each = rows.groupBy("platform_id", "worker_id", "g", "m", panel.alias("panel")).agg(
        F.count("*").alias("messages"), F.coalesce(F.max("gap"), F.lit(0)).cast("bigint").alias("longest"), F.sum(F.when(F.col("gap") > panel, 1).otherwise(0)).alias("starved")
    )
    need = F.col("g") * F.col("g") + 2 * F.col("g") * (1 + F.floor((F.greatest("longest", F.lit(1)) + F.col("panel") - 1) / F.col("panel"))).cast("bigint")
    return each.select("platform_id", "worker_id", "messages", "longest", "starved", need.alias("need"), (need <= F.col("m")).alias("fits"))
