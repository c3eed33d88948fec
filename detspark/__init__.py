"""Selected-configuration-interaction engine expressed as Spark dataflow."""
