"""The queue run against hand-worked examples, a millisecond-stepped simulator, and properties."""

import random

import pytest

from elastipool.model import FIGURE, NEVER, PEAK, SEQUENTIAL, STATIC2, RunConfig
from elastipool.functions.control import step
from elastipool.operators.kernel import run_queue


def stepped(tasks, cfg, horizon):
    """Every millisecond in turn: completions, arrivals, poll, each followed by dispatch."""
    idle, busy, queue, out, polls = list(range(1, cfg.n_init + 1)), {}, [], {}, []
    n, nid, t_last, done, last = cfg.n_init, cfg.n_init + 1, NEVER, 0, 0

    def dispatch(t):
        while idle and queue:
            queue.sort()
            prio, seq, svc = queue.pop(0)
            w = min(idle)
            idle.remove(w)
            busy[w] = t + svc
            out[seq] = (t, t + svc, w)

    for t in range(horizon):
        for w in sorted(w for w, f in busy.items() if f == t):
            del busy[w]
            idle.append(w)
            done, last = done + 1, t
            dispatch(t)
        for seq, prio, enq, svc in tasks:
            if enq == t:
                queue.append((prio, seq, svc))
                dispatch(t)
        if cfg.autoscale and t and t % cfg.poll_ms == 0:
            d = step(len(queue), len(busy), n, t, t_last, cfg)
            polls.append((t, len(queue), len(busy), n, d))
            for _ in range(d):
                idle.append(nid)
                nid += 1
            for _ in range(-d):
                idle.remove(max(idle))
            n, t_last = n + d, t if d else t_last
            dispatch(t)
            if done == len(tasks) and t >= last + cfg.tail_ms:
                break
    return out, polls


def test_worked_example_priority_and_fifo():
    cfg = RunConfig(n_init=1, n_min=1, n_max=1, autoscale=False)
    tasks = [(0, 2, 0, 10), (1, 2, 1, 5), (2, 1, 2, 4)]
    out, _ = run_queue(tasks, cfg)
    assert out == {0: (0, 10, 1), 2: (10, 14, 1), 1: (14, 19, 1)}
    out, _ = run_queue([(s, 1, e, v) for s, _, e, v in tasks], cfg)
    assert out == {0: (0, 10, 1), 1: (10, 15, 1), 2: (15, 19, 1)}


def test_worked_example_controller():
    n, last, seen = 2, NEVER, []
    for t in range(1000, 17_000, 1000):
        d = step(9, n, n, t, last, FIGURE)
        if d:
            seen.append((t, n + d))
            n, last = n + d, t
    assert seen == [(1000, 4), (6000, 6), (11_000, 8)] and last == 11_000


@pytest.mark.parametrize("seed", range(6))
def test_against_stepped(seed):
    rng = random.Random(seed)
    cfg = FIGURE.but(n_init=rng.choice([1, 2, 3]), n_min=1, n_max=rng.choice([3, 5]), poll_ms=rng.choice([7, 20]), cooldown_ms=rng.choice([0, 25]), queue_hi=rng.choice([1, 3]), tail_ms=60, step=rng.choice([1, 2]), step_down=rng.choice([1, 2]))
    enq = sorted(rng.randrange(0, 150) for _ in range(40))
    tasks = [(i, rng.randrange(1, 4), e, rng.randrange(1, 40)) for i, e in enumerate(enq)]
    out, polls = run_queue(tasks, cfg)
    want, seen = stepped(tasks, cfg, 5000)
    assert out == want
    assert [(t, q, b, n, d) for _, t, q, b, n, d, *_ in polls] == seen


@pytest.mark.parametrize("cfg", [FIGURE, STATIC2, SEQUENTIAL, PEAK, FIGURE.but(cooldown_ms=0)])
def test_properties(cfg):
    rng = random.Random(3)
    tasks = [(i, rng.randrange(1, 4), i * 40, rng.randrange(100, 3000)) for i in range(300)]
    out, polls = run_queue(tasks, cfg)
    assert len(out) == 300
    by = {}
    for s, (a, z, w) in out.items():
        assert a >= tasks[s][2] and z - a == tasks[s][3]
        by.setdefault(w, []).append((a, z))
    for spans in by.values():
        spans.sort()
        assert all(x[1] <= y[0] for x, y in zip(spans, spans[1:]))
    last = NEVER
    for _, t, q, busy, n, d, after, _, _ in polls:
        assert cfg.n_min <= after <= cfg.n_max and abs(d) <= cfg.step and 0 <= busy <= n and q <= 300
        if d:
            assert t - last >= cfg.cooldown_ms
            last = t


def test_scaling_time_scales_results():
    tasks = [(i, 1 + i % 3, i * 30, 200 + 7 * i % 90) for i in range(80)]
    a, _ = run_queue(tasks, FIGURE.but(poll_ms=50, cooldown_ms=100, tail_ms=100))
    b, _ = run_queue([(s, p, 3 * e, 3 * v) for s, p, e, v in tasks], FIGURE.but(poll_ms=150, cooldown_ms=300, tail_ms=300))
    assert {s: (3 * x, 3 * y, w) for s, (x, y, w) in a.items()} == b


def test_empty_and_spinup():
    assert run_queue([], FIGURE) == ({}, [])
    assert run_queue([], STATIC2) == ({}, [])
    tasks = [(i, 1, 0, 5000) for i in range(30)]
    slow, _ = run_queue(tasks, FIGURE.but(spinup_ms=4000))
    fast, _ = run_queue(tasks, FIGURE)
    assert max(f for _, f, _ in slow.values()) > max(f for _, f, _ in fast.values())




def test_run_holds_waiting_tasks_only():
    """Tasks are taken as they come and results leave as they start, so a shard's length costs no memory: 100,000 tasks that never queue up."""
    import tracemalloc

    import pyarrow as pa

    from elastipool.operators import kernel

    def batches():
        for k in range(0, 100_000, 10_000):
            i = range(k, k + 10_000)
            yield pa.RecordBatch.from_pydict({"run_id": ["elastic"] * 10_000, "shard": [0] * 10_000, "enq_ms": [x * 1000 for x in i], "seq": list(i), "prio": [1] * 10_000, "svc_ms": [500] * 10_000, "task_id": list(i)})

    tracemalloc.start()
    n = sum(b.column("kind").to_pylist().count("result") for b in kernel._run({"elastic": FIGURE})(batches()))
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert n == 100_000 and most < 30_000_000


def test_tasks_without_priority_come_last():
    from elastipool.operators import kernel

    got = [r[1] for r in kernel.served([(0, 0, None, 100, 0), (0, 1, 3, 100, 1), (0, 2, -1, 100, 2), (0, 3, 3, 100, 3)], STATIC2.but(n_init=1)) if r[0] == "result"]
    assert got == [0, 2, 1, 3]
