"""Reading tables, writing results, and stage tables between jobs."""
