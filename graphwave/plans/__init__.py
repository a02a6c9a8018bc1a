"""Planning: lineage, broadcast gates, costs, measures and the SQL texts of the oracles."""
