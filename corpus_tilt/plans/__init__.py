"""Our own small plan layer and the SQL chains of the queries."""
