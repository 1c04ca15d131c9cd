"""Private mining of frequent graph patterns on Spark."""
