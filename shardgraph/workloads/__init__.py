"""The paper's experiments on the given tables, as queries with oracle SQL."""
