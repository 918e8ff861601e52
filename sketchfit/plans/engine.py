"""Which physical way builds a sketch."""

from __future__ import annotations

#: Above this many features a flat aggregate costs more to compile than to run.
MAX_SQL_FEATURES = 64


def pick_engine(fm, engine: str = "auto", clip: float | None = None) -> str:
    """sql: flat sums in generated code; summarizer: vector sums in the JVM; arrow: matrix products on Arrow batches with partial sums.

    All three combine on the map side. A grouped Python aggregate does not, and is never used for sketches.
    """
    if engine == "auto":
        return "sql" if fm.has_columns and fm.m <= MAX_SQL_FEATURES else "arrow"
    if engine not in ("sql", "summarizer", "arrow"):
        raise ValueError(f"unknown engine {engine}")
    if engine != "arrow" and not fm.has_columns:
        raise ValueError(f"{fm.kind} has no column form; use the arrow engine")
    if engine == "summarizer" and clip is not None:
        raise ValueError("clipping needs the sql or arrow engine")
    return engine
