"""Write-saving sorting, transforms and products on Spark, with exact read and write ledgers."""
