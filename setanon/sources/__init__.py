"""Record sets, query logs and corpora from tables, and sinks for released data."""
