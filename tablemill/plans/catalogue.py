"""All registered queries of the library proper."""

from tablemill.plans import agent, basics, contrasts, corpus, encoder, evaluation, factory, sources, streams, tables, workloads
from tablemill.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "agent", "basics", "contrasts", "corpus", "encoder", "evaluation", "factory", "sources", "streams", "tables", "workloads"]
