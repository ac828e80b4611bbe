"""Analytics on Spark for graphs whose edges are valid during a time interval."""
