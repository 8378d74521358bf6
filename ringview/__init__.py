"""ringview: analytics over joins of changing tables, as trees of ring-valued views kept up to date by Spark."""
