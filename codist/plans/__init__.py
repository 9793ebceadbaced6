"""Training driver, physical choices, workloads, measures of cost, and the catalogue of queries."""
