"""framepatterns: distributed dataframe operator patterns, expressed natively on Spark."""
