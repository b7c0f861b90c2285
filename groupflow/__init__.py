"""groupflow: moving-group discovery over trajectory streams, as Spark plans."""
