"""The threshold rule as Column expressions, as a Python step for the kernel, and as SQL functions.

All arithmetic is in integers: busy / n > 0.8 is ``1000 * busy > 800 * n``, so Spark and any other engine agree bit for bit.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from elastipool.model import RunConfig


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def cooled(t, t_last, cfg: RunConfig) -> Column:
    return (_c(t) - _c(t_last)) >= cfg.cooldown_ms


def c_up(q, busy, n, cfg: RunConfig) -> Column:
    over = F.lit(False)
    if cfg.use_queue:
        over = over | (_c(q) > cfg.queue_hi)
    if cfg.use_util:
        over = over | (_c(busy) * 1000 > _c(n) * cfg.util_hi_pm)
    return over


def c_down(q, busy, n, cfg: RunConfig) -> Column:
    return (_c(q) == 0) & (_c(busy) * 1000 < _c(n) * cfg.util_lo_pm)


def clip(n, cfg: RunConfig) -> Column:
    return F.least(F.greatest(_c(n), F.lit(cfg.n_min)), F.lit(cfg.n_max))


def delta(q, busy, n, t, t_last, cfg: RunConfig) -> Column:
    """Change of the pool: at most ``step`` up inside the bounds, at most ``step_down`` workers down (idle ones, unless the pool drains), 0 while cooling down."""
    up = F.least(F.lit(cfg.step), F.lit(cfg.n_max) - _c(n))
    down = -F.least(F.lit(cfg.step_down), _c(n) - cfg.n_min, *([] if cfg.retire == "drain" else [_c(n) - _c(busy)]))
    return F.when(~cooled(t, t_last, cfg), 0).when(c_up(q, busy, n, cfg), up).when(c_down(q, busy, n, cfg), down).otherwise(0).cast("int")


def step(q: int, busy: int, n: int, t: int, t_last: int, cfg) -> int:
    """The rule for one poll; ``cfg`` is anything with the fields of RunConfig."""
    if not cfg.autoscale or t - t_last < cfg.cooldown_ms:
        return 0
    signal = busy * cfg.cpu_share_pm // 1000 if cfg.cpu_share_pm else busy
    if (cfg.use_queue and q > cfg.queue_hi) or (cfg.use_util and signal * 1000 > n * cfg.util_hi_pm):
        return min(cfg.step, cfg.n_max - n)
    if q == 0 and signal * 1000 < n * cfg.util_lo_pm:
        return -min(cfg.step_down, n - cfg.n_min, *([] if cfg.retire == "drain" else [n - busy]))
    return 0


def register_sql(spark: SparkSession, cfg: RunConfig) -> None:
    """``scale_delta(q, busy, n, elapsed)`` for SQL users: the rule as a temporary SQL function, inlined by the optimiser."""
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION scale_delta(q INT, busy INT, n INT, elapsed BIGINT) RETURNS INT RETURN
      CASE WHEN elapsed < {cfg.cooldown_ms} THEN 0 WHEN q > {cfg.queue_hi} OR busy * 1000 > n * {cfg.util_hi_pm} THEN least({cfg.step}, {cfg.n_max} - n)
           WHEN q = 0 AND busy * 1000 < n * {cfg.util_lo_pm} THEN -least({cfg.step_down}, n - {cfg.n_min}, n - busy) ELSE 0 END""")
