"""closeway: crowd-informed road routing as Spark DataFrame plans."""
