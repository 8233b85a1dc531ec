"""Every method, variant, measure and workload as a named query, with its SQL."""

from . import matrices, products, relational, studies

QUERIES = matrices.QUERIES | products.QUERIES | studies.QUERIES | relational.QUERIES
ORACLES = matrices.ORACLES | products.ORACLES | studies.ORACLES | relational.ORACLES
