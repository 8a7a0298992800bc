"""Plans: compiling rules to edges, staging, the query catalogue and its SQL."""
