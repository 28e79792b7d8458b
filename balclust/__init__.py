"""PySpark engine for capacity-bounded clustering summaries and the operators around them."""
