"""Reading the given tables, and the corpora of the experiments."""

from .corpora import dna, log, vocabulary
from .tables import dealt, load

__all__ = ["dealt", "dna", "load", "log", "vocabulary"]
