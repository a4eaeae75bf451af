"""Local mass diffusion: threshold push, full sweep, and the hybrid that chooses per seed and round.

State rows are (seed_id, node_id, deg, residual, reserve) with the seed's settings beside them; a node without a
row has nothing. In a round,

* a row is *hot* when residual >= eps * degree;
* *threshold push* moves the hot rows, a *sweep* moves every row with residual; moving keeps 1 - alpha of the residual and
  spreads alpha of it over the neighbours;
* *hybrid* sweeps when the hot share of rows with residual is over sigma and what sweeps have cost so far, with this
  one, stays under mass / ((1 - alpha) * eps).

``alpha`` is the probability of moving on. Three engines give the same result:

* ``local``: a seed's explored neighbourhood is gathered in one NumPy worker (see ``ball``), for seeds whose bound is small;
* ``rounds``: each round is one job over all seeds. What a seed's round does comes from partial sums a seed; only
  moving rows meet the packed adjacency, whose other buckets aren't read;
* ``unrolled``: a fixed number of rounds in one plan, by a window over the seed.

``auto`` takes ``local`` where 2 mass / ((1 - alpha) eps), or the whole graph, is under ``ball.MOST_EDGES`` edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from attrgraph.operators.graph import BROADCAST_BYTES, ROW_BYTES, Graph, Packed, adjacency
from attrgraph.session import discard, materialise

ALPHA = 0.8
STATE = ["seed_id", "node_id", "deg", "residual", "reserve", "eps", "budget", "spent"]


def start_unit(seeds: DataFrame) -> DataFrame:
    """Unit mass on each seed."""
    return seeds.select("seed_id", F.col("seed_id").alias("node_id"), F.lit(1.0).alias("mass"))


def start_weighted(rows: DataFrame) -> DataFrame:
    """Any non-negative start (seed_id, node_id, mass); a negative mass raises when the plan runs."""
    checked = F.when(F.col("mass") < 0, F.raise_error(F.lit("start mass must not be negative")).cast("double")).otherwise(F.col("mass"))
    return rows.select("seed_id", "node_id", checked.cast("double").alias("mass")).where("mass > 0")


def initial(g: Graph, start: DataFrame, alpha: float, eps: float | str, relative_eps: bool, budget_cap: float | None) -> DataFrame:
    """State before the first round. ``eps`` is a number or the name of a column of ``start``."""
    base = start.groupBy("seed_id", "node_id").agg(F.sum("mass").alias("residual"), *([F.max(eps).alias("eps0")] if isinstance(eps, str) else []))
    seed = Window.partitionBy("seed_id")
    mass = F.sum("residual").over(seed)
    level = (F.col("eps0") if isinstance(eps, str) else F.lit(float(eps))) * (mass if relative_eps else F.lit(1.0))
    rows = base.select("seed_id", "node_id", "residual", level.alias("eps"), mass.alias("mass"))
    budget = F.lit(float(budget_cap)) if budget_cap is not None else F.col("mass") / ((1 - alpha) * F.col("eps"))
    rows = rows.join(g.degrees, "node_id")
    return rows.select("seed_id", "node_id", "deg", "residual", F.lit(0.0).alias("reserve"), "eps", budget.alias("budget"), F.lit(0.0).alias("spent"))


def advance(state: DataFrame, packed: DataFrame, alpha: float, sigma: float) -> DataFrame:
    """One round in one plan that refers to the state once."""
    seed = Window.partitionBy("seed_id")
    hot = F.col("residual") >= F.col("eps") * F.col("deg")
    some = F.col("residual") > 0
    told = state.withColumns({"hot": hot & some})
    told = told.withColumns({
        "n_hot": F.sum(F.col("hot").cast("long")).over(seed),
        "n_some": F.sum(some.cast("long")).over(seed),
        "vol": F.sum(F.when(some, F.col("deg")).otherwise(0.0)).over(seed),
    })
    sweep = (F.col("n_hot") > 0) & (F.col("n_hot") / F.col("n_some") > sigma) & (F.col("spent") + F.col("vol") < F.col("budget"))
    told = told.withColumn("sweep", sweep).withColumn("active", F.col("hot") | (F.col("sweep") & some))
    told = told.withColumn("spent", F.col("spent") + F.when(F.col("sweep"), F.col("vol")).otherwise(0.0)).withColumn("at", F.when(F.col("active"), F.col("node_id")))
    joined = told.join(packed.withColumnRenamed("node_id", "at"), "at", "left")
    first = F.coalesce(F.col("chunk"), F.lit(-1)) <= 0  # a hub has a row for each chunk: its own part counts once
    own = F.struct(
        F.col("node_id"), F.col("deg"),
        F.when(~first | F.col("active"), 0.0).otherwise(F.col("residual")).alias("residual"),
        F.when(first, F.col("reserve") + F.when(F.col("active"), (1 - alpha) * F.col("residual")).otherwise(0.0)).otherwise(0.0).alias("reserve"),
    )
    sent = F.transform(F.coalesce("nb", F.array().cast(packed.schema["nb"].dataType)), lambda x: F.struct(x["dst"].alias("node_id"), x["deg"].alias("deg"), (F.lit(alpha) * F.col("residual") * x["p"]).alias("residual"), F.lit(0.0).alias("reserve")))
    rows = joined.select("seed_id", "eps", "budget", "spent", F.explode(F.concat(F.array(own), sent)).alias("r"))
    # the settings are the same on all rows of a seed, so they are grouped by, not aggregated
    return rows.groupBy("seed_id", "r.node_id").agg(
        F.max("r.deg").alias("deg"), F.sum("r.residual").alias("residual"), F.sum("r.reserve").alias("reserve"),
        F.max("eps").alias("eps"), F.max("budget").alias("budget"), F.max("spent").alias("spent"),
    )


def settings(strategy: str, sigma: float) -> tuple[float, float | None]:
    """(sigma, cap on the budget) that make one round formula serve the three strategies."""
    if strategy == "threshold":
        return 1.0, None
    if strategy == "sweep":
        return 0.0, float("inf")
    if strategy == "hybrid":
        if not 0 <= sigma <= 1:
            raise ValueError("sigma is in [0, 1]")
        return float(sigma), None
    raise ValueError(f"no strategy {strategy}")


def advance_kept(state: DataFrame, packed: Packed, alpha: float, sigma: float) -> DataFrame | None:
    """One round from a written state to a written state; None when nothing is hot.

    A row a seed comes from partial sums; it is joined back, broadcast where the counted seeds are few.
    """
    some = F.col("residual") > 0
    hot = some & (F.col("residual") >= F.col("eps") * F.col("deg"))
    per = state.groupBy("seed_id").agg(
        F.sum(hot.cast("long")).alias("n_hot"), F.sum(some.cast("long")).alias("n_some"), F.sum(F.when(some, F.col("deg")).otherwise(0.0)).alias("vol"),
        F.max("spent").alias("spent"), F.max("budget").alias("budget"),
    )
    sweep = (F.col("n_hot") > 0) & (F.col("n_hot") / F.col("n_some") > sigma) & (F.col("spent") + F.col("vol") < F.col("budget"))
    per = per.withColumn("sweep", sweep).select("seed_id", "sweep", (F.col("spent") + F.when(sweep, F.col("vol")).otherwise(0.0)).alias("spent_now"), F.when(sweep, F.col("n_some")).otherwise(F.col("n_hot")).alias("n"))
    per = materialise(per, "seeds")
    total = per.agg(F.sum("n").alias("n"), F.count("*").alias("seeds")).first()
    if not total.n:
        discard(per)
        return None
    few = total.seeds * ROW_BYTES <= BROADCAST_BYTES
    told = state.join(F.broadcast(per) if few else per, "seed_id")
    active = hot | (F.col("sweep") & some)
    moving = materialise(told.where(active).select("seed_id", "node_id", "residual", "eps", "budget", "spent_now"), "moving")
    near = packed.of(moving.select("node_id").distinct())
    small = total.n * ROW_BYTES <= BROADCAST_BYTES
    out = near.join(F.broadcast(moving) if small else moving, "node_id").select("seed_id", "eps", "budget", F.col("spent_now").alias("spent"), "residual", F.explode("nb").alias("to"))
    sent = out.select("seed_id", F.col("to.dst").alias("node_id"), F.col("to.deg").alias("deg"), (F.lit(alpha) * F.col("residual") * F.col("to.p")).alias("residual"), F.lit(0.0).alias("reserve"), "eps", "budget", "spent")
    own = told.select("seed_id", "node_id", "deg", F.when(active, 0.0).otherwise(F.col("residual")).alias("residual"), (F.col("reserve") + F.when(active, (1 - alpha) * F.col("residual")).otherwise(0.0)).alias("reserve"), "eps", "budget", F.col("spent_now").alias("spent"))
    both = own.union(sent).groupBy("seed_id", "node_id").agg(*[(F.sum if c in ("residual", "reserve") else F.max)(c).alias(c) for c in STATE[2:]])
    after = materialise(both, "state")
    for done in (per, moving):
        discard(done)
    return after


def diffuse(
    g: Graph, start: DataFrame, alpha: float = ALPHA, eps: float | str = 1e-3, strategy: str = "hybrid", sigma: float = 0.1,
    relative_eps: bool = False, engine: str = "auto", rounds: int = 60, trace: list | None = None, most_rounds: int | None = None,
) -> DataFrame:
    """(seed_id, node_id, deg, residual, reserve, eps, budget, spent) after the last round.

    Reserve is the diffused mass: 0 <= exact - reserve <= eps * deg at every node. Start rows whose node isn't in
    the graph are left out (a seed without edges has no walk). All engines but ``unrolled`` run until no row is hot; that one
    chains exactly ``rounds`` rounds, of which those past the end change nothing. ``most_rounds`` ends the others after so many
    rounds, hot rows or not; without it nothing is left hot. With ``trace`` (rounds engine), a dict
    for each seed and round is appended to the list; that is a row per seed on the driver, in batches of seeds.
    """
    sigma, cap = settings(strategy, sigma)
    if engine == "unrolled":
        packed, state = adjacency(g), initial(g, start, alpha, eps, relative_eps, cap)
        for _ in range(rounds):
            state = advance(state, packed, alpha, sigma)
        return state
    g = g.kept()
    state = materialise(initial(g, start, alpha, eps, relative_eps, cap), "state")
    if engine == "auto":
        from attrgraph.operators.ball import MOST_EDGES

        most = state.agg(F.max("budget")).first()[0] or 0.0
        engine = "local" if trace is None and min(2 * most, g.size) <= MOST_EDGES else "rounds"
    if engine == "local":
        from attrgraph.operators.ball import diffuse_in_balls

        return diffuse_in_balls(g, state, alpha, sigma, most_rounds=most_rounds)
    return run_rounds(g, state, alpha, sigma, trace, most_rounds)


def run_rounds(g: Graph, state: DataFrame, alpha: float, sigma: float, trace: list | None = None, most_rounds: int | None = None) -> DataFrame:
    """Rounds from a written state until nothing is hot or ``most_rounds`` are done, each one job."""
    done = 0
    while most_rounds is None or done < most_rounds:
        if trace is not None:
            trace += _told(state, done + 1, sigma)
        after = advance_kept(state, g.packed, alpha, sigma)
        if after is None:
            return state
        discard(state)
        state, done = after, done + 1
    return state


def _told(state: DataFrame, number: int, sigma: float) -> list[dict]:
    hot = (F.col("residual") > 0) & (F.col("residual") >= F.col("eps") * F.col("deg"))
    rows = state.groupBy("seed_id").agg(
        F.sum(hot.cast("long")).alias("n_hot"), F.sum((F.col("residual") > 0).cast("long")).alias("n_supp"), F.sum(F.when(F.col("residual") > 0, F.col("deg")).otherwise(0.0)).alias("vol_supp"),
        F.sum(F.when(hot, F.col("deg")).otherwise(0.0)).alias("vol_hot"), F.max("spent").alias("spent"), F.max("budget").alias("budget"), F.sum("residual").alias("residual_sum"),
    ).collect()
    out = []
    for r in rows:
        sweep = r.n_hot > 0 and r.n_hot / r.n_supp > sigma and r.spent + r.vol_supp < r.budget
        out.append(r.asDict() | {"round": number, "mode": "end" if not r.n_hot else "sweep" if sweep else "push", "pushed": 0.0 if not r.n_hot else r.vol_supp if sweep else r.vol_hot})
    return out


def trace_frame(g: Graph, start: DataFrame, **options) -> DataFrame:
    """(seed_id, round, mode, n_hot, n_supp, vol_supp, spent, pushed, residual_sum) of every round of ``diffuse``.

    A seed's rows go on to its end or the last round; where it ends before others do, to the last end of any.
    """
    rows: list[dict] = []
    diffuse(g, start, trace=rows, **options)
    ends: dict = {}
    for r in rows:
        if r["mode"] == "end":
            ends.setdefault(r["seed_id"], r["round"])
    rows = [r for r in rows if r["seed_id"] not in ends or r["round"] <= max(ends.values())]
    fields = "seed_id long, round int, mode string, n_hot long, n_supp long, vol_supp double, spent double, pushed double, residual_sum double"
    names = [f.split()[0] for f in fields.split(", ")]
    return start.sparkSession.createDataFrame([tuple(r[n] for n in names) for r in rows], fields)


def scores(state: DataFrame) -> DataFrame:
    """(seed_id, node_id, score, deg): the positive reserves."""
    return state.where("reserve > 0").select("seed_id", "node_id", F.col("reserve").alias("score"), "deg")
