"""SQL of an independent implementation of sampling, tasks and the queue run: used only to check the engine, never by it.

The run is a recursive query with one row for each event; its state is kept in lists.
"""

from __future__ import annotations

from elastipool.model import DEFAULT, DIFFERENT_PM, EVENT_PRIORITY, HINTS, LETTERS_PM, LEXICON, N_EVAL, NEVER, ROLES, SEED, WORD_WEIGHT, ArrivalSpec, RunConfig

SOURCES = {
    "lang": "SELECT doc_id, text, lang AS y, n_chars, source FROM documents WHERE lang IS NOT NULL",
    "quality": "SELECT d.doc_id, text, CASE WHEN quality = 0 THEN 'junk' ELSE 'clean' END AS y, n_chars, source FROM documents d JOIN labels USING (doc_id)",
    "toxic": "SELECT d.doc_id, text, CASE WHEN toxic = 1 THEN 'toxic' ELSE 'ok' END AS y, n_chars, source FROM documents d JOIN labels USING (doc_id)",
}
PRIO = {
    "source": "CAST(CAST(regexp_extract(source, '([0-9]+)', 1) AS INTEGER) % 3 + 1 AS INTEGER)",
    "label": "CAST(ascii(y) % 3 + 1 AS INTEGER)",
    "const": "CAST(1 AS INTEGER)",
}


def src(task: str) -> str:
    return f"src AS ({SOURCES[task]})"


def reps() -> str:
    return "reps AS (SELECT md5(text) AS text_md5, min(doc_id) AS doc_id, arg_min(y, doc_id) AS y, arg_min(n_chars, doc_id) AS n_chars, arg_min(source, doc_id) AS source FROM src GROUP BY 1)"


def samp(n: int = N_EVAL, seed: int = SEED) -> str:
    return f"""cls AS (SELECT count(*) AS classes, min(c) AS least FROM (SELECT y, count(*) AS c FROM reps GROUP BY y)),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY y ORDER BY md5('{seed}:' || doc_id), doc_id) AS r FROM reps),
    samp AS (SELECT doc_id, y, n_chars, source, text_md5, CAST(r AS INTEGER) AS r FROM ranked, cls WHERE r <= least({n} // classes, least // 2))"""


def prop(n: int = N_EVAL, seed: int = SEED) -> str:
    return f"""cnt AS (SELECT y, count(*) AS c FROM reps GROUP BY y), tot AS (SELECT CAST(sum(c) AS BIGINT) AS total FROM cnt),
    quo AS (SELECT y, c, total, least({n}, total // 2) AS size FROM cnt, tot),
    quo2 AS (SELECT *, (c * size) // total AS base, row_number() OVER (ORDER BY (c * size) % total DESC, y) AS o FROM quo),
    quo3 AS (SELECT y, base + CASE WHEN o <= size - sum(base) OVER () THEN 1 ELSE 0 END AS quota FROM quo2),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY y ORDER BY md5('{seed}:' || doc_id), doc_id) AS r FROM reps),
    samp AS (SELECT doc_id, y, n_chars, source, text_md5, CAST(r AS INTEGER) AS r FROM ranked JOIN quo3 USING (y) WHERE r <= quota)"""


def arrival(seq: str, n: str, spec: ArrivalSpec = ArrivalSpec()) -> str:
    b, s, tb = spec.burst_pm * spec.ratio_tenths, (1000 - spec.burst_pm) * 10, spec.window_ms * spec.burst_pm // 1000
    nb = f"(({n} * {b} + {(b + s) // 2}) // {b + s})"
    return f"CAST(CASE WHEN {seq} < {nb} THEN ({seq} * {tb}) // greatest({nb}, 1) ELSE {tb} + (({seq} - {nb}) * {spec.window_ms - tb}) // greatest({n} - {nb}, 1) END AS BIGINT)"


def service(role: str) -> str:
    base, us = ROLES[role]
    return f"CAST(greatest({base} + (n_chars * {us}) // 1000, 1) AS BIGINT)"


def tasks(role: str = "zs_fast", prio: str = "source", spec: ArrivalSpec = ArrivalSpec(), seed: int = SEED) -> str:
    return f"""num AS (SELECT *, row_number() OVER (ORDER BY md5('{seed}:' || doc_id), doc_id) - 1 AS seq, count(*) OVER () AS n_all FROM samp),
    tk AS (SELECT 0 AS shard, doc_id AS task_id, CAST(seq AS BIGINT) AS seq, {PRIO[prio]} AS prio, {arrival("seq", "n_all", spec)} AS enq_ms, {service(role)} AS svc_ms, y, n_chars FROM num)"""


def base(task: str = "lang", role: str = "zs_fast", prio: str = "source", spec: ArrivalSpec = ArrivalSpec()) -> str:
    return ", ".join([src(task), reps(), samp(), tasks(role, prio, spec)])


def sim(cfg: RunConfig, tag: str = "", tasks_: str = "tk") -> str:
    """CTEs res{tag} and pol{tag} of one run over the tasks named."""
    auto = "true" if cfg.autoscale else "false"
    drain, spin = cfg.retire == "drain", cfg.spinup_ms > 0
    if drain and spin:
        raise ValueError("one of draining and spin-up")
    busy = "(len(run) - len(lv))" if drain else "len(run)"
    signal = f"(({busy} * {cfg.cpu_share_pm}) // 1000)" if cfg.cpu_share_pm else busy
    down = f"least({cfg.step_down}, n - {cfg.n_min}{'' if drain else ', n - len(run)'})"
    # draining and starting workers: one more list in the state
    more0 = ", CAST([] AS BIGINT[]) AS lv" if drain else ", CAST([] AS STRUCT(finish BIGINT, worker BIGINT)[]) AS wk" if spin else ""
    gone = "least(len(idle), -d)"
    more1 = ""
    if drain:
        more1 = f""", CASE WHEN ev2 = 'c' THEN [x FOR x IN lv IF x <> br.worker] WHEN ev2 = 'p' AND d < 0 THEN list_concat(lv,
          list_slice(list_reverse_sort([x.worker FOR x IN run IF NOT list_contains(lv, x.worker)]), 1, -d - {gone})) ELSE lv END"""
    if spin:
        more1 = f""", CASE WHEN ev2 = 'w' THEN list_sort(wk)[2:] WHEN ev2 = 'p' AND d > 0 THEN list_concat(wk, [{{'finish': m + {cfg.spinup_ms}, 'worker': x}} FOR x IN CAST(range(nid, nid + d) AS BIGINT[])])
          WHEN ev2 = 'p' AND d < 0 THEN list_slice(list_sort(wk), 1, len(wk) + d + {gone}) ELSE wk END"""
    back = "CASE WHEN list_contains(lv, br.worker) THEN idle ELSE list_append(idle, br.worker) END" if drain else "list_append(idle, br.worker)"
    new = "idle" if spin else "list_concat(idle, CAST(range(nid, nid + d) AS BIGINT[]))"
    waking = "WHEN 'w' THEN list_append(idle, list_sort(wk)[1].worker) " if spin else ""
    over = " OR ".join([f"len(q) > {cfg.queue_hi}"] * cfg.use_queue + [f"{signal} * 1000 > n * {cfg.util_hi_pm}"] * cfg.use_util)
    d = f"""CASE WHEN NOT {auto} OR m - tl < {cfg.cooldown_ms} THEN 0 WHEN {over} THEN least({cfg.step}, {cfg.n_max} - n)
        WHEN len(q) = 0 AND {signal} * 1000 < n * {cfg.util_lo_pm} THEN -{down} ELSE 0 END"""
    far = 1 << 60
    return f"""
    arr{tag} AS (SELECT list({{'enq': enq_ms, 'prio': prio, 'seq': seq, 'svc': svc_ms}} ORDER BY enq_ms, seq) AS l, count(*) AS n_all FROM {tasks_}),
    sim{tag} AS (
      SELECT 0 AS k, 'init' AS ev, CAST(0 AS BIGINT) AS t, CAST([] AS STRUCT(prio INTEGER, seq BIGINT, svc BIGINT)[]) AS q, CAST([] AS STRUCT(finish BIGINT, worker BIGINT)[]) AS run,
        CAST(range(1, {cfg.n_init + 1}) AS BIGINT[]) AS idle, CAST({cfg.n_init} AS BIGINT) AS n, CAST({cfg.n_init + 1} AS BIGINT) AS nid, CAST({NEVER} AS BIGINT) AS tl, CAST(0 AS BIGINT) AS ai, CAST(0 AS BIGINT) AS done, CAST(0 AS BIGINT) AS last, CAST(1 AS BIGINT) AS j,
        CAST(NULL AS BIGINT) AS o_seq, CAST(NULL AS BIGINT) AS o_fin, CAST(NULL AS BIGINT) AS o_worker, CAST(NULL AS BIGINT) AS p_q, CAST(NULL AS BIGINT) AS p_busy, CAST(NULL AS BIGINT) AS p_n, CAST(NULL AS BIGINT) AS p_d{more0}
      UNION ALL
      SELECT k + 1, ev2, CASE WHEN ev2 = 'd' THEN t ELSE m END,
        CASE ev2 WHEN 'd' THEN [x FOR x IN q IF x.seq <> bq.seq] WHEN 'a' THEN list_append(q, {{'prio': na.prio, 'seq': na.seq, 'svc': na.svc}}) ELSE q END,
        CASE ev2 WHEN 'd' THEN list_append(run, {{'finish': t + bq.svc, 'worker': bw}}) WHEN 'c' THEN [x FOR x IN run IF x.worker <> br.worker] ELSE run END,
        CASE ev2 WHEN 'd' THEN [x FOR x IN idle IF x <> bw] WHEN 'c' THEN {back} {waking}
          WHEN 'p' THEN CASE WHEN d > 0 THEN {new} WHEN d < 0 THEN list_slice(list_sort(idle), 1, len(idle) - {gone}) ELSE idle END ELSE idle END,
        CASE WHEN ev2 = 'p' THEN n + d ELSE n END, CASE WHEN ev2 = 'p' AND d > 0 THEN nid + d ELSE nid END, CASE WHEN ev2 = 'p' AND d <> 0 THEN m ELSE tl END,
        CASE WHEN ev2 = 'a' THEN ai + 1 ELSE ai END, CASE WHEN ev2 = 'c' THEN done + 1 ELSE done END, CASE WHEN ev2 = 'c' THEN m ELSE last END, CASE WHEN ev2 = 'p' THEN j + 1 ELSE j END,
        CASE WHEN ev2 = 'd' THEN bq.seq END, CASE WHEN ev2 = 'd' THEN t + bq.svc END, CASE WHEN ev2 = 'd' THEN bw END,
        CASE WHEN ev2 = 'p' THEN len(q) END, CASE WHEN ev2 = 'p' THEN {busy} END, CASE WHEN ev2 = 'p' THEN n END, CASE WHEN ev2 = 'p' THEN d END{more1}
      FROM (SELECT *, {d} AS d FROM (SELECT *, CASE WHEN len(idle) > 0 AND len(q) > 0 THEN 'd' WHEN tf = m THEN 'c' {"WHEN tw = m THEN 'w' " * spin}WHEN ta = m THEN 'a' ELSE 'p' END AS ev2 FROM (
        SELECT *, least(tf, ta, tp{", tw" * spin}) AS m FROM (
          SELECT s.*, a.n_all, list_sort(q)[1] AS bq, list_min(idle) AS bw, list_sort(run)[1] AS br, a.l[ai + 1] AS na, coalesce(list_sort(run)[1].finish, {far}) AS tf, coalesce(a.l[ai + 1].enq, {far}) AS ta, CASE WHEN {auto} THEN j * {cfg.poll_ms} ELSE {far} END AS tp{f", coalesce(list_sort(wk)[1].finish, {far}) AS tw" * spin}
          FROM sim{tag} s, arr{tag} a)
        WHERE NOT (done = n_all AND (NOT {auto} OR (j > 1 AND (j - 1) * {cfg.poll_ms} >= last + {cfg.tail_ms}))))))
    ),
    res{tag} AS (SELECT '{cfg.run_id}' AS run_id, k.shard, k.task_id, k.seq, k.prio, k.enq_ms, k.svc_ms, s.t AS start_ms, s.o_fin AS finish_ms, CAST(s.o_worker AS INTEGER) AS worker_id, s.t - k.enq_ms AS wait_ms, s.o_fin - k.enq_ms AS sojourn_ms, k.y, k.n_chars
      FROM sim{tag} s JOIN {tasks_} k ON s.o_seq = k.seq WHERE s.ev = 'd'),
    pol{tag} AS (SELECT '{cfg.run_id}' AS run_id, 0 AS shard, CAST(j - 1 AS INTEGER) AS j, t AS t_ms, p_q AS q, CAST(p_busy AS INTEGER) AS busy, CAST(p_n AS INTEGER) AS n_before, CAST(p_d AS INTEGER) AS delta, CAST(p_n + p_d AS INTEGER) AS n_after, done, tl AS t_last_ms, CAST((p_busy * 1000) // p_n AS INTEGER) AS util_pm
      FROM sim{tag} WHERE ev = 'p')"""


def elastic(cfg: RunConfig, select: str, task: str = "lang", role: str = "zs_fast", prio: str = "source") -> str:
    return f"WITH RECURSIVE {base(task, role, prio)}, {sim(cfg)} {select}"


class Sized(str):
    """A number that the query itself computes, where a configuration has a literal."""

    def __add__(self, k):
        return Sized(f"({self} + {k})")


def sizes(spec: ArrivalSpec = ArrivalSpec(), tasks_: str = "tk") -> str:
    burst = spec.window_ms * spec.burst_pm // 1000
    up = lambda what, t: f"CAST(greatest((sum({what}) + {t - 1}) // {t}, 1) AS INTEGER)"
    return f"size AS (SELECT {up('svc_ms', spec.window_ms)} AS average, {up(f'CASE WHEN enq_ms < {burst} THEN svc_ms ELSE 0 END', burst)} AS peak FROM {tasks_})"


def sized(cfg: RunConfig, which: str) -> RunConfig:
    n = Sized(f"(SELECT {which} FROM size)")
    return cfg.but(n_init=n, n_min=n, n_max=n)


def several(cfgs: list[tuple[RunConfig, str]], select: str, task: str = "lang", prio: str = "source", more: str = "") -> str:
    """Runs of (configuration, role) over one sample, united as res and pol; sequential passes take tasks in arrival order. ``more`` are further tables made from the tasks."""
    parts = [src(task), reps(), samp()]
    order = lambda c: "const" if c.n_init == 1 and not c.autoscale else prio
    for r, p in sorted({(r, order(c)) for c, r in cfgs}):
        parts.append(tasks(r, p).replace("num AS", f"num_{r}_{p} AS").replace("tk AS", f"tk_{r}_{p} AS").replace("FROM num)", f"FROM num_{r}_{p})"))
    if more:
        parts.append(more)
    for i, (c, r) in enumerate(cfgs):
        parts.append(sim(c, f"_{i}", f"tk_{r}_{order(c)}"))
    for kind in ("res", "pol"):
        parts.append(f"{kind} AS (" + " UNION ALL ".join(f"SELECT * FROM {kind}_{i}" for i in range(len(cfgs))) + ")")
    return f"WITH RECURSIVE {', '.join(parts)} {select}"


def words(task: str, label: str) -> str:
    w = LEXICON[task][label]
    return f"len([x FOR x IN tok IF x IN ({', '.join(repr(v) for v in w)})])" if w else "0"


LETTERS = r"length(regexp_replace(text, '[^\p{L}]', '', 'g')) * 1000 < length(text) * " + str(LETTERS_PM)
SAME = f"len(list_distinct(tok)) * 1000 < len(tok) * {DIFFERENT_PM}"


def label(role: str, task: str) -> str:
    """The label of a role that reads the text: an expression over ``text`` and its words ``tok`` (and ``doc_id``)."""
    if role == "hash":
        ys = list(LEXICON[task])
        return f"list_value({', '.join(repr(y) for y in ys)})[CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 4) AS INTEGER) % {len(ys)} + 1]"
    if role == "zs_weak":
        return zs(task, weak=True)
    if task == "quality":
        return f"CASE WHEN {LETTERS}{f' OR {SAME}' if role == 'zs_heavy' else ''} THEN 'junk' ELSE 'clean' END"
    return heavy(task) if role == "zs_heavy" else zs(task)


def heavy(task: str) -> str:
    s = {}
    for y in LEXICON[task]:
        hints = HINTS[task][y]
        s[y] = f"({words(task, y)} * {WORD_WEIGHT} + " + (f"len([x FOR x IN tok IF regexp_matches(x, '{'|'.join(hints)}')]))" if hints else "0)")
    return _case(s, DEFAULT[task])


def zs(task: str, weak: bool = False) -> str:
    """CASE expression over a list column ``tok``."""
    return _case({y: (f"len([x FOR x IN tok IF x = '{y}'])" if weak else words(task, y)) for y in LEXICON[task]}, DEFAULT[task])


def _case(s: dict[str, str], default: str) -> str:
    best = f"greatest({', '.join(s.values())})"
    return f"CASE WHEN {best} <= 0 THEN '{default}' " + " ".join(f"WHEN {v} = {best} THEN '{y}'" for y, v in s.items()) + " END"


TOK = r"[x FOR x IN regexp_split_to_array(lower(text), '[^\p{L}]+') IF x <> '']"
EVENT_PRIO = "CAST(CASE event_type " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in EVENT_PRIORITY.items()) + " ELSE 9 END AS INTEGER)"
