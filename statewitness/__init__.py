"""statewitness: a PySpark engine that audits stateful tools against what they advertise."""
