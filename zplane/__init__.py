"""zplane: exact spatial queries over Morton planes, as PySpark plans."""
