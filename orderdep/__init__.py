"""Discovery, validation and use of order dependencies on Spark."""
