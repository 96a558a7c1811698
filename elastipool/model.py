"""Fixed vocabulary of the engine: run configuration, arrival curve, roles, label spaces. Times are integer milliseconds, ratios per mille.

Virtual clock. At equal times completions come before arrivals, arrivals before polls; completions go by worker id, arrivals by sequence. After each event
queued tasks go to idle workers, lowest id first, least (priority, sequence) first. Polls are at poll_ms, 2 poll_ms, ...; the last one is the first at or
after the final completion plus tail_ms. Scale-in removes the highest-numbered idle workers; new workers take the next unused id.
"""

from __future__ import annotations

from dataclasses import asdict, dataclass, replace

NEVER = -1_000_000_000
SEED = 17


@dataclass(frozen=True)
class RunConfig:
    run_id: str = "elastic"
    n_init: int = 2
    n_min: int = 2
    n_max: int = 8
    queue_hi: int = 5
    util_hi_pm: int = 800
    util_lo_pm: int = 200
    step: int = 2
    step_down: int = 2
    poll_ms: int = 1000
    cooldown_ms: int = 5000
    tail_ms: int = 10_000
    lat_window: int = 200
    autoscale: bool = True
    use_queue: bool = True
    use_util: bool = True
    cpu_share_pm: int = 0
    spinup_ms: int = 0
    retire: str = "idle"  # or "drain": busy workers may be told to leave after their task

    def but(self, **changes) -> RunConfig:
        return replace(self, **changes)

    def as_row(self) -> dict:
        return asdict(self)


@dataclass(frozen=True)
class ArrivalSpec:
    """Burst of ``burst_pm`` of the window at ``ratio_tenths`` times the steady rate."""

    window_ms: int = 180_000
    burst_pm: int = 380
    ratio_tenths: int = 48


FIGURE = RunConfig(n_init=4)
TEXT = RunConfig(n_init=2)
STATIC2 = RunConfig(run_id="static", n_init=2, n_min=2, n_max=2, autoscale=False)
SEQUENTIAL = RunConfig(run_id="sequential", n_init=1, n_min=1, n_max=1, autoscale=False)
PEAK = RunConfig(run_id="peak", n_init=8, n_min=8, n_max=8, autoscale=False)

#: Service model of each role: fixed part in ms and microseconds a character; calibrated so that the fast role takes 13.7 s on average.
ROLES = {"zs_fast": (12_000, 700), "zs_heavy": (36_000, 2100), "zs_weak": (12_000, 700), "supervised": (6000, 350), "majority": (1000, 0), "hash": (1000, 0)}

#: Words that speak for a label, in label order; ties go to the earlier label.
LEXICON = {
    "lang": {
        "de": ("der", "die", "und", "das", "ist", "nicht", "ein", "zu", "von", "mit", "sich", "auf", "dem", "den", "im"),
        "en": ("the", "of", "and", "to", "is", "that", "for", "with", "was", "it", "this", "are", "as", "by", "from"),
        "es": ("el", "los", "las", "y", "una", "por", "con", "del", "se", "su", "al", "lo", "para", "como"),
        "fr": ("le", "les", "et", "est", "des", "une", "dans", "qui", "pour", "du", "au", "sur", "pas", "avec"),
    },
    "toxic": {"ok": (), "toxic": ("idiot", "moron", "stupid", "trash", "loser", "scum", "clown", "worthless", "pathetic", "disgusting")},
    "quality": {"clean": (), "junk": ()},
}
#: Letter groups that speak for a language, and beginnings of words that speak for toxicity: the further evidence of the heavy role.
HINTS = {
    "lang": {
        "de": ("sch", "ung$", "ß", "ä", "ö", "ü", "^ge", "ich"), "en": ("th", "ing$", "^wh", "ght", "ly$", "ed$"),
        "es": ("ción", "ñ", "^ll", "ado$", "dad$", "á", "ó", "í"), "fr": ("eau", "ç", "ê", "è", "aux$", "ment$", "oi"),
    },
    "toxic": {"ok": (), "toxic": ("^idiot", "^moron", "^stup", "^trash", "^loser", "^scum", "^clown", "^worthl", "^pathet", "^disgust")},
}
#: What one word of the lexicon counts for, against one of a hint.
WORD_WEIGHT = 3
#: Shape rules, per mille: least share of letters, and least share of different words.
LETTERS_PM, DIFFERENT_PM = 735, 450
#: The class taken without evidence, and the class whose recall is watched.
DEFAULT = {"lang": "en", "toxic": "ok", "quality": "clean"}
POSITIVE = {"toxic": "toxic", "quality": "junk"}
EVENT_PRIORITY = {"error": 1, "purchase": 2, "signup": 3, "click": 4, "view": 5}
N_EVAL, N_TRAIN, N_MARKS = 200, 4000, 40
