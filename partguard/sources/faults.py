"""Fault plans on the event table: pure column expressions, written once and read by Spark and by other SQL engines alike."""

from __future__ import annotations

from dataclasses import dataclass, field

SEVERITY = {3: 12, 2: 6, 1: 3}  # of twenty rows
CORRUPTING = ("null_out", "minus_one", "stuck_flag", "typo", "label_drop")
BENIGN = ("garbage_minor", "outlier_1pct", "weekend", "holiday")
#: Faulted days of January 2024 by level.
LOW_DAYS = {3: (10, 15, 20, 24, 28), 2: (13, 22), 1: (17, 26, 30)}
HIGH_DAYS = {3: (9, 10, 12, 13, 15, 16, 18, 19, 21, 23, 24, 27, 29), 2: (26,), 1: (11, 17, 22, 30)}


@dataclass(frozen=True)
class FaultPlan:
    """Which fault acts on which day, and how hard: {day: (level, fault)}; and benign changes, which are no corruption."""

    name: str
    days: dict[int, tuple[int, str]] = field(default_factory=dict)
    benign: tuple[str, ...] = ()

    def when(self, fault: str) -> str:
        """SQL condition on a row (``ts``, ``event_id``): the fault acts on it."""
        parts = []
        for level, rows in SEVERITY.items():
            if days := sorted(d for d, (lv, f) in self.days.items() if f == fault and lv == level):
                parts.append(f"(day(ts) IN ({', '.join(map(str, days))}) AND event_id % 20 < {rows})")
        return "(" + " OR ".join(parts) + ")" if parts else "(1 = 0)"

    def level_of(self, day: int) -> int:
        return self.days.get(day, (0, ""))[0]

    def truth(self, level: int) -> set[int]:
        """Days that are corrupted at this level or a harder one."""
        return {d for d, (lv, _) in self.days.items() if lv >= level}

    def columns(self, json_k: str) -> dict[str, str]:
        """SQL of the faulted columns v, et, k, stuck, clicked over (event_id, ts, user_id, event_type, value, props); ``json_k`` is the dialect's integer at key k."""
        value = "value"
        if "outlier_1pct" in self.benign:
            value = f"CASE WHEN event_id % 100 = 0 THEN {value} * 1000 ELSE {value} END"
        if "weekend" in self.benign:
            value = f"CASE WHEN day(ts) % 7 IN (6, 0) THEN ({value}) * 1.5 ELSE ({value}) END"
        if "holiday" in self.benign:
            value = f"CASE WHEN day(ts) = 25 THEN ({value}) * 2 ELSE ({value}) END"
        label = self.when("label_drop")
        k = f"CASE WHEN day(ts) % 3 = 0 THEN (event_id * 7919) % 100000 ELSE {json_k} END" if "garbage_minor" in self.benign else json_k
        band = "CASE WHEN value < 5 THEN 50 WHEN value < 20 THEN 150 WHEN value < 50 THEN 350 ELSE 650 END"
        return {
            "v": f"CASE WHEN {self.when('null_out')} THEN NULL WHEN {self.when('minus_one')} THEN -1.0 ELSE ({value}) END",
            "et": f"CASE WHEN {self.when('typo')} THEN concat(event_type, '_x') WHEN {label} AND event_type = 'purchase' THEN 'view' ELSE event_type END",
            "k": k,
            "stuck": f"CASE WHEN {self.when('stuck_flag')} THEN 1 ELSE 0 END",
            "clicked": f"CASE WHEN {label} THEN 0 WHEN (event_id * 7919) % 1000 < {band} THEN 1 ELSE 0 END",
        }


def _days(levels: dict[int, tuple[int, ...]], faults: tuple[str, ...]) -> dict[int, tuple[int, str]]:
    every = sorted((d, lv) for lv, days in levels.items() for d in days)
    return {d: (lv, faults[i % len(faults)]) for i, (d, lv) in enumerate(every)}


CLEAN = FaultPlan("clean")
LOW = FaultPlan("low", _days(LOW_DAYS, CORRUPTING))
HIGH = FaultPlan("high", _days(HIGH_DAYS, CORRUPTING))


def single(fault: str, which: str = "low") -> FaultPlan:
    """One fault alone, on the days of the low or high plan; or one benign change on a clean table."""
    if fault in BENIGN:
        return FaultPlan(fault, {}, (fault,))
    return FaultPlan(f"{which}_{fault}", _days(LOW_DAYS if which == "low" else HIGH_DAYS, (fault,)))


PLANS = {p.name: p for p in (CLEAN, LOW, HIGH, *(single(f) for f in (*CORRUPTING, *BENIGN)))}
