"""unischema: attribute and schema integration with literal and concept joins, on Spark."""
