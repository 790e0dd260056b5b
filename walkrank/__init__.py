"""walkrank: approximate heaviest-vertex ranking with discrete walkers on Spark."""
