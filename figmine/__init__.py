"""figmine: a Spark-native engine for mining pictorial regions out of digitised page collections."""
