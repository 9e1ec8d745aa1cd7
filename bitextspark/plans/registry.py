"""All queries of the methods and their companions."""

from . import q_companion, q_eval, q_filters, q_models, q_training

FAMILIES = (q_filters, q_models, q_eval, q_training, q_companion)
QUERIES = {name: f for family in FAMILIES for name, f in family.QUERIES.items()}
SQL = {name: text for family in FAMILIES for name, text in family.SQL.items()}
