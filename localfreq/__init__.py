"""localfreq: itemsets that are frequent inside particular time intervals, with those exact intervals, on Spark."""
