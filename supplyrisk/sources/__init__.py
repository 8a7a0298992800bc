"""Where build histories come from and go to: tables, mappings, graph files."""
