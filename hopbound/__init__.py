"""hopbound: bounded-length simple path and cycle enumeration on Spark."""
