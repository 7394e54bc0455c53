"""All queries of the library but those of the corpus operators."""

from . import paper, relational, tuning

QUERIES = paper.QUERIES | relational.QUERIES | tuning.QUERIES
ORACLES = paper.ORACLES | relational.ORACLES | tuning.ORACLES
