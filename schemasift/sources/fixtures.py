"""The logical databases over the given tables: declared keys, questions and gold statements. Fixed values."""

TABLES = ["benchmark", "conversations", "customer", "documents", "embeddings", "events", "labels", "lineitem", "nation", "orders", "pages", "part", "region", "supplier"]
DATABASES = {
    "retail7": ["customer", "lineitem", "nation", "orders", "part", "region", "supplier"],
    "web": ["conversations", "events", "pages"],
    "text": ["benchmark", "documents", "embeddings", "labels"],
    "all14": TABLES,
}
PRIMARY_KEYS = {
    "region": ["r_regionkey"], "nation": ["n_nationkey"], "customer": ["c_custkey"], "supplier": ["s_suppkey"], "part": ["p_partkey"], "orders": ["o_orderkey"], "events": ["event_id"],
    "documents": ["doc_id"], "embeddings": ["vec_id"], "pages": ["page_id"], "benchmark": ["item_id"], "labels": ["doc_id"], "conversations": ["conv_id", "turn"],
}
FOREIGN_KEYS = [
    ("customer", "c_nationkey", "nation", "n_nationkey"), ("labels", "doc_id", "documents", "doc_id"), ("lineitem", "l_orderkey", "orders", "o_orderkey"), ("lineitem", "l_partkey", "part", "p_partkey"),
    ("lineitem", "l_suppkey", "supplier", "s_suppkey"), ("nation", "n_regionkey", "region", "r_regionkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("supplier", "s_nationkey", "nation", "n_nationkey"),
]
#: The columns of the given tables, for the SQL side.
COLUMNS = {
    "benchmark": "item_id:bigint text:string",
    "conversations": "conv_id:bigint turn:bigint role:string text:string",
    "customer": "c_custkey:bigint c_name:string c_nationkey:int c_acctbal:double c_mktsegment:string",
    "documents": "doc_id:bigint text:string lang:string source:string n_chars:bigint",
    "embeddings": "vec_id:bigint embedding:array<float> label:int",
    "events": "event_id:bigint ts:timestamp_ntz user_id:bigint event_type:string value:double props:string",
    "labels": "doc_id:bigint quality:int toxic:int",
    "lineitem": "l_orderkey:bigint l_partkey:bigint l_suppkey:bigint l_linenumber:int l_quantity:double l_extendedprice:double l_discount:double l_tax:double l_returnflag:string l_linestatus:string l_shipdate:timestamp_ntz",
    "nation": "n_nationkey:int n_name:string n_regionkey:int",
    "orders": "o_orderkey:bigint o_custkey:bigint o_orderstatus:string o_totalprice:double o_orderdate:timestamp_ntz o_orderpriority:string",
    "pages": "page_id:bigint url:string html:string",
    "part": "p_partkey:bigint p_name:string p_brand:string p_type:string p_size:int p_retailprice:double",
    "region": "r_regionkey:int r_name:string",
    "supplier": "s_suppkey:bigint s_name:string s_nationkey:int s_acctbal:double",
}
QUESTIONS = [
    ("q01", "How many orders are there per order status?", "SELECT o_orderstatus, COUNT(*) AS n FROM orders GROUP BY o_orderstatus"),
    ("q02", "List the names of customers in the MACHINERY market segment with a negative account balance.", "SELECT c_name FROM customer WHERE c_mktsegment = 'MACHINERY' AND c_acctbal < 0"),
    ("q03", "How many nations does each region have?", "SELECT r_name, COUNT(n_nationkey) AS n FROM region JOIN nation ON n_regionkey = r_regionkey GROUP BY r_name"),
    ("q04", "Number of customers located in NATION_7.", "SELECT COUNT(c_custkey) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_name = 'NATION_7'"),
    ("q05", "What is the average account balance of suppliers per nation name?", "SELECT n_name, AVG(s_acctbal) AS a FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name"),
    ("q06", "Total quantity shipped for each part brand.", "SELECT p_brand, SUM(l_quantity) AS s FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"),
    ("q07", "Total order price per market segment of the customer.", "SELECT c_mktsegment, SUM(o_totalprice) AS s FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"),
    ("q08", "Count the urgent orders placed by customers of each nation.", "SELECT n_name, COUNT(o_orderkey) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o_orderpriority = '1-URGENT' GROUP BY n_name"),
    ("q09", "Revenue after discount of line items by order priority for shipments after 1998.", "SELECT o_orderpriority, SUM(l_extendedprice * (1 - l_discount)) AS rev FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate >= TIMESTAMP '1999-01-01 00:00:00' GROUP BY o_orderpriority"),
    ("q10", "Total order price of customers in ASIA.", "SELECT SUM(o_totalprice) AS s FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'"),
    ("q11", "Which part brands are supplied from EUROPE?", "SELECT DISTINCT p_brand FROM part JOIN lineitem ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'EUROPE'"),
    ("q12", "Names of customers that ordered parts of type PROMO.", "SELECT DISTINCT c_name FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE p_type = 'PROMO'"),
    ("q13", "How many distinct suppliers served customers in the BUILDING segment?", "SELECT COUNT(DISTINCT s_suppkey) AS n FROM supplier JOIN lineitem ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING'"),
    ("q14", "Sum of discount times price for returned items (return flag R).", "SELECT SUM(l_extendedprice * l_discount) AS s FROM lineitem WHERE l_returnflag = 'R'"),
    ("q15", "How many purchase events does each user have?", "SELECT user_id, COUNT(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY user_id"),
    ("q16", "Average value of events by event type per day.", "SELECT event_type, CAST(ts AS DATE) AS d, AVG(value) AS a FROM events GROUP BY event_type, CAST(ts AS DATE)"),
    ("q17", "How many toxic documents are there per language?", "SELECT lang, COUNT(*) AS n FROM documents JOIN labels ON documents.doc_id = labels.doc_id WHERE toxic = 1 GROUP BY lang"),
    ("q18", "Average number of characters of high quality documents by source.", "SELECT source, AVG(n_chars) AS a FROM documents JOIN labels ON documents.doc_id = labels.doc_id WHERE quality = 1 GROUP BY source"),
    ("q19", "How many turns does each conversation have for the assistant role?", "SELECT conv_id, COUNT(turn) AS n FROM conversations WHERE role = 'assistant' GROUP BY conv_id"),
    ("q20", "How many vectors carry each label?", "SELECT label, COUNT(vec_id) AS n FROM embeddings GROUP BY label"),
    ("q21", "List the page urls that contain a query string.", "SELECT url FROM pages WHERE url LIKE '%?%'"),
    ("q22", "Nations that have customers but no suppliers.", "SELECT c_nationkey AS nk FROM customer EXCEPT SELECT s_nationkey AS nk FROM supplier"),
    ("q23", "For every customer, the most expensive order.", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, ROW_NUMBER() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) t WHERE rn = 1"),
    ("q24", "Suppliers that shipped red widgets.", "SELECT s_name FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_name = 'red widget')"),
]
#: Columns that each gold statement needs, by question.
GOLD = {
    "q01": "orders.o_orderstatus",
    "q02": "customer.c_acctbal customer.c_mktsegment customer.c_name",
    "q03": "nation.n_nationkey nation.n_regionkey region.r_name region.r_regionkey",
    "q04": "customer.c_custkey customer.c_nationkey nation.n_name nation.n_nationkey",
    "q05": "nation.n_name nation.n_nationkey supplier.s_acctbal supplier.s_nationkey",
    "q06": "lineitem.l_partkey lineitem.l_quantity part.p_brand part.p_partkey",
    "q07": "customer.c_custkey customer.c_mktsegment orders.o_custkey orders.o_totalprice",
    "q08": "customer.c_custkey customer.c_nationkey nation.n_name nation.n_nationkey orders.o_custkey orders.o_orderkey orders.o_orderpriority",
    "q09": "lineitem.l_discount lineitem.l_extendedprice lineitem.l_orderkey lineitem.l_shipdate orders.o_orderkey orders.o_orderpriority",
    "q10": "customer.c_custkey customer.c_nationkey nation.n_nationkey nation.n_regionkey orders.o_custkey orders.o_totalprice region.r_name region.r_regionkey",
    "q11": "lineitem.l_partkey lineitem.l_suppkey nation.n_nationkey nation.n_regionkey part.p_brand part.p_partkey region.r_name region.r_regionkey supplier.s_nationkey supplier.s_suppkey",
    "q12": "customer.c_custkey customer.c_name lineitem.l_orderkey lineitem.l_partkey orders.o_custkey orders.o_orderkey part.p_partkey part.p_type",
    "q13": "customer.c_custkey customer.c_mktsegment lineitem.l_orderkey lineitem.l_suppkey orders.o_custkey orders.o_orderkey supplier.s_suppkey",
    "q14": "lineitem.l_discount lineitem.l_extendedprice lineitem.l_returnflag",
    "q15": "events.event_type events.user_id",
    "q16": "events.event_type events.ts events.value",
    "q17": "documents.doc_id documents.lang labels.doc_id labels.toxic",
    "q18": "documents.doc_id documents.n_chars documents.source labels.doc_id labels.quality",
    "q19": "conversations.conv_id conversations.role conversations.turn",
    "q20": "embeddings.label embeddings.vec_id",
    "q21": "pages.url",
    "q22": "customer.c_nationkey supplier.s_nationkey",
    "q23": "orders.o_custkey orders.o_orderkey orders.o_totalprice",
    "q24": "lineitem.l_partkey lineitem.l_suppkey part.p_name part.p_partkey supplier.s_name supplier.s_suppkey",
}
#: Descriptions that come with the data; the other columns have none.
OBSERVED = {("customer", "c_mktsegment"): "Market segment of the customer.", ("orders", "o_orderpriority"): "Priority class of the order.", ("documents", "lang"): "Language code of the text.", ("lineitem", "l_returnflag"): "Whether the item came back."}
#: The worked example's four tables, each beside the one that it refers to or is referred to by: students, enrollments, courses and
#: departments are part, lineitem, supplier and nation.
CAMPUS = ["part", "lineitem", "supplier", "nation"]
