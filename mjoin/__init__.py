"""Multi-relation inequality joins on Spark, planned and scheduled as few region jobs."""
