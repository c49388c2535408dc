"""The change feed around an index: churn, late rows, last values, rebuild triggers."""
