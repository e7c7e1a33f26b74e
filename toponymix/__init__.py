"""Place-alias discovery on Spark: footprints of place names, their similarity, and what follows from it."""
