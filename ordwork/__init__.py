"""ordwork: ordered graph work on Spark. One rule, many orders."""
