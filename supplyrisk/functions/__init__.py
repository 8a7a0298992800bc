"""Column functions: status lattice, rule tables, versions, SQL functions."""
