"""Ways to cut a plan: tables in the folder that driver and executors share."""
