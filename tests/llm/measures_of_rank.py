from __future__ import annotations


def auc(pairs) -> float:
    """Area under the curve of (score, label) pairs."""
    good, bad = [s for s, y in pairs if y], [s for s, y in pairs if not y]
    return sum((g > b) + 0.5 * (g == b) for g in good for b in bad) / (len(good) * len(bad))
