"""Group-biased marker analytics on Spark: panels, association tests, posteriors, triage."""
