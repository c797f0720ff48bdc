"""Private, communication-light entropy estimation on Spark."""
