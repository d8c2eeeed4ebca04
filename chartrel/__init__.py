"""chartrel: relations between the axes of pictured charts, computed with Spark."""
