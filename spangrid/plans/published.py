"""Published rates (queries per second) that the mixed-workload measures are recomputed from."""

#: Fixed values. For each dataset and kind of query, in the order of METHODS.
METHODS = ("start_first", "duration_first", "uniform_grid", "replicating", "packed_tree", "interval_tree", "ordered_duration")
RATES = {
    "synthetic": {"range_only": (415, 602, 468, 242, 12, 272, 8), "duration_only": (842, 734, 77, 69, 106, 12, 43103), "range_duration": (11737, 14085, 1581, 1403, 2591, 215, 502)},
    "flights": {"range_only": (54945, 57471, 49505, 15015, 4921, 51813, 2798), "duration_only": (4182, 4218, 3791, 538, 378, 683, 714286), "range_duration": (232558, 208333, 188679, 29940, 21786, 43860, 13514)},
    "edits": {"range_only": (416, 467, 445, 83, 30, 384, 47), "duration_only": (2544, 2520, 1938, 57, 234, 157, 3393), "range_duration": (3159, 3133, 2322, 80, 258, 256, 758)},
    "clinical": {"range_only": (372, 391, 391, 381, 38, 347, 127), "duration_only": (3560, 2876, 2075, 520, 452, 76, 2500000), "range_duration": (10246, 10730, 5227, 1779, 1384, 232, 3347)},
}


def rows() -> list[tuple]:
    """(dataset, method, pos, range_only, duration_only, range_duration)."""
    return [(d, m, i, *(float(r[k][i]) for k in ("range_only", "duration_only", "range_duration"))) for d, r in RATES.items() for i, m in enumerate(METHODS)]


def values_sql() -> str:
    return "SELECT * FROM (VALUES " + ", ".join(f"('{d}', '{m}', {i}, {a:.1f}::DOUBLE, {b:.1f}::DOUBLE, {c:.1f}::DOUBLE)" for d, m, i, a, b, c in rows()) + ") v(dataset, method, pos, range_only, duration_only, range_duration)"
