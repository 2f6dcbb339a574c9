"""All registered queries."""

from beamrank.plans import ablation_queries, beam_queries, learned_queries, measured_queries, relational_queries, sql_queries, stream_queries, text_queries  # noqa: F401
from beamrank.plans.registry import QUERIES, oracle_texts  # noqa: F401
