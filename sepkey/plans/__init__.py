"""Catalogues, workloads, measures and the registered queries."""
